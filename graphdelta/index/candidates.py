"""Support-counted candidate sets over a rooted tree or DAG of the pattern, kept from batch to batch.

For every directed pattern edge (p, c) the index counts, per data vertex, its neighbours that are root-side candidates
of p (``up``) and those that are full candidates of c (``down``).  A vertex is a root-side candidate when its label
fits and every root-side edge has a count; it is a full candidate when every sink-side edge has one too.  A batch
changes counts by the batch's own arcs under the old flags, plus the arcs of those vertices whose flag turned; both
walks follow the fixed vertex order once.  Counts and flags are ledgers: a batch appends what it changes and looks up
only the vertices it touches, so its work does not grow with the index but for scans that filter.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.index.ledger import Ledger
from graphdelta.pattern.model import Pattern
from graphdelta.pattern.shape import Rooted
from graphdelta.plans.relations import Change, relation
from graphdelta.sources.storage import cut

Edge = tuple[int, int]


def read_from(arcs: DataFrame, q: Pattern, p: int, c: int) -> DataFrame:
    """Arcs that fit the pattern edge between p and c, as (src on p's side, dst on c's side)."""
    e = q.edge_between(p, c)
    rel = relation(arcs, q, e).select("src", "dst")
    return rel if q.edges[e][0] == p else rel.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def both(sides: list[DataFrame]) -> DataFrame:
    """(vid) that all sides have."""
    return reduce(lambda a, b: a.join(b, "vid", "left_semi"), sides)


def as_vid(df: DataFrame, column: str) -> DataFrame:
    return df.select(F.col(column).alias("vid"))


@dataclass
class CandidateIndex:
    """Flags and counts for one snapshot; ``top_down`` is off for the bottom-up-only index."""

    q: Pattern
    shape: Rooted
    vertices: DataFrame
    top_down: bool = True
    n_up: dict[Edge, Ledger] = field(default_factory=dict)
    n_down: dict[Edge, Ledger] = field(default_factory=dict)
    up: dict[int, Ledger] = field(default_factory=dict)
    down: dict[int, Ledger] = field(default_factory=dict)

    def labelled(self, u: int) -> DataFrame:
        label = self.q.vlabels[u]
        return (self.vertices if label is None else self.vertices.filter(F.col("vlabel") == label)).select("vid")

    @staticmethod
    def build(q: Pattern, shape: Rooted, arcs: DataFrame, vertices: DataFrame, top_down: bool = True) -> CandidateIndex:
        """Forward pass along the order, then backward pass; every table is written."""
        ix = CandidateIndex(q, shape, vertices, top_down)
        counted = lambda near, side: Ledger(cut(as_vid(near, side).groupBy("vid").agg(F.count(F.lit(1)).alias("n")), "counts"))
        one = lambda vids: vids.withColumn("n", F.lit(1).cast("long"))
        for u in shape.order:
            parents = shape.parents[u] if top_down else ()
            for p in parents:
                ix.n_up[p, u] = counted(read_from(arcs, q, p, u).join(ix.up[p].vids().withColumnRenamed("vid", "src"), "src", "left_semi"), "dst")
            flags = one(both([ix.labelled(u), *[ix.n_up[p, u].vids() for p in parents]]))
            ix.up[u] = Ledger(cut(flags, "flags") if parents else flags)
        for u in reversed(shape.order):
            for c in shape.children[u]:
                ix.n_down[u, c] = counted(read_from(arcs, q, u, c).join(ix.down[c].vids().withColumnRenamed("vid", "dst"), "dst", "left_semi"), "src")
            ix.down[u] = Ledger(cut(one(both([ix.up[u].vids(), *[ix.n_down[u, c].vids() for c in shape.children[u]]])), "flags")) if shape.children[u] else ix.up[u]
        return ix

    def updated(self, change: Change, only: int | None = None) -> CandidateIndex:
        """The index after a batch, from changed counts only; ``only`` takes the batch as arcs of one query edge alone.

        Taking the query edges one after the other (upwards for insertions, downwards for deletions) gives the states
        between the telescoped terms; relations of edges not yet taken are then without an inserted batch, or with a
        deleted one.
        """
        q, new = self.q, CandidateIndex(self.q, self.shape, self.vertices, self.top_down)

        def arcs_after(p: int, c: int) -> DataFrame:
            e = q.edge_between(p, c)
            taken = only is None or (e <= only if change.sign > 0 else e >= only)
            return change.after if taken else change.base

        def moved(counts: Ledger, p: int, c: int, near: str, far: str, flags: Ledger, turned: DataFrame | None) -> tuple[Ledger, DataFrame | None]:
            """A count ledger after flags on side ``far`` turned and, if it is its turn, the batch's arcs came or went."""
            parts = []
            if only is None or q.edge_between(p, c) == only:
                own = read_from(change.delta, q, p, c)
                ends = flags.of(as_vid(own, far).distinct()).withColumnRenamed("vid", far)
                parts.append(own.join(ends, far).select(F.col(near).alias("vid"), F.lit(change.sign).cast("long").alias("n")))
            if turned is not None:
                spread = read_from(arcs_after(p, c), q, p, c).join(turned.withColumnRenamed("vid", far), far)
                parts.append(spread.select(F.col(near).alias("vid"), "n"))
            if not parts:
                return counts, None
            step = cut(reduce(DataFrame.unionByName, parts).groupBy("vid").agg(F.sum("n").alias("n")).filter("n != 0"), "step")
            return counts.plus(step), step

        def turn(old: Ledger, label_side: DataFrame | Ledger, sides: list[Ledger], touched: list[DataFrame]) -> tuple[Ledger, DataFrame | None]:
            """A flag ledger after its sides changed at the touched vertices, and which flags turned."""
            if not touched:
                return old, None
            vids = reduce(DataFrame.unionByName, [t.select("vid") for t in touched]).distinct()
            was = old.of(vids)
            first = label_side.of(vids) if isinstance(label_side, Ledger) else label_side.join(vids, "vid", "left_semi")
            now = both([first, *[s.of(vids) for s in sides]])
            came, went = now.join(was, "vid", "left_anti"), was.join(now, "vid", "left_anti")
            turned = cut(came.withColumn("n", F.lit(1).cast("long")).unionByName(went.withColumn("n", F.lit(-1).cast("long"))), "turned")
            return old.plus(turned), turned

        up_turned: dict[int, DataFrame | None] = {}
        for u in self.shape.order:
            touched = []
            for p in self.shape.parents[u] if self.top_down else ():
                new.n_up[p, u], step = moved(self.n_up[p, u], p, u, "dst", "src", self.up[p], up_turned[p])
                touched += [step] if step is not None else []
            new.up[u], up_turned[u] = turn(self.up[u], self.labelled(u), [new.n_up[p, u] for p in self.shape.parents[u] if self.top_down], touched)
        turned: dict[int, DataFrame | None] = {}
        for u in reversed(self.shape.order):
            touched = [up_turned[u]] if up_turned[u] is not None else []
            for c in self.shape.children[u]:
                new.n_down[u, c], step = moved(self.n_down[u, c], u, c, "src", "dst", self.down[c], turned[c])
                touched += [step] if step is not None else []
            if self.shape.children[u]:
                new.down[u], turned[u] = turn(self.down[u], new.up[u], [new.n_down[u, c] for c in self.shape.children[u]], touched)
            else:
                new.down[u], turned[u] = new.up[u], up_turned[u]
        return new

    def keep(self, rows: DataFrame, column: str, u: int) -> DataFrame:
        """The rows (a written table) whose ``column`` is a full candidate of u."""
        return rows.join(self.down[u].of(as_vid(rows, column).distinct()).withColumnRenamed("vid", column), column, "left_semi").select(*rows.columns)

    def prune(self, e: int, rel: DataFrame) -> DataFrame:
        """A query relation with both ends among the full candidates."""
        u, w, _ = self.q.edges[e]
        src, dst = (self.down[x].vids().withColumnRenamed("vid", side) for x, side in ((u, "src"), (w, "dst")))
        return rel.join(src, "src", "left_semi").join(dst, "dst", "left_semi").select(*rel.columns)

    def pruned(self, change: Change) -> dict[int, DataFrame]:
        """The part of every query relation that a match with a batch edge can use.

        From the batch's arcs the candidates that lie within reach are walked through, as many steps as the pattern has
        vertices beyond two; a walk scans the arcs against a small table, and only what it reaches is written, as one table.
        """
        every = change.full.select("src", "dst", "slabel", "dlabel", "elabel")
        fit = reduce(lambda a, b: a | b, [_fits(self.q, e, back) for e in range(self.q.m) for back in (False, True)])
        useful = every.filter(fit).select("src", "dst")
        near = cut(as_vid(change.delta, "src").distinct(), "near")
        for _ in range(self.q.n - 2):
            step = useful.join(near.withColumnRenamed("vid", "src"), "src", "left_semi")
            near = cut(as_vid(step, "dst").unionByName(near).distinct(), "near")
        held = {u: self.down[u].of(near) for u in range(self.q.n)}
        parts = []
        for e, (u, w, _) in enumerate(self.q.edges):
            src, dst = held[u].withColumnRenamed("vid", "src"), held[w].withColumnRenamed("vid", "dst")
            parts.append(relation(change.arcs, self.q, e).join(src, "src", "left_semi").join(dst, "dst", "left_semi").select(F.lit(e).alias("q_edge"), "src", "dst", "new"))
        every = cut(reduce(DataFrame.unionByName, parts), "pruned")
        return {e: every.filter(F.col("q_edge") == e).drop("q_edge") for e in range(self.q.m)}

    def flags(self) -> DataFrame:
        """(u, vid, up, down) of every root-side candidate."""
        parts = []
        for u in range(self.q.n):
            full = self.down[u].vids().withColumn("down", F.lit(True))
            parts.append(self.up[u].vids().join(full, "vid", "left").select(F.lit(u).alias("u"), "vid", F.lit(True).alias("up"), F.coalesce("down", F.lit(False)).alias("down")))
        return reduce(DataFrame.unionByName, parts)

    def counts(self) -> DataFrame:
        """Full candidates of every pattern vertex."""
        return reduce(DataFrame.unionByName, [self.down[u].vids().agg(F.count(F.lit(1)).alias("n_candidates")).select(F.lit(u).alias("u"), "n_candidates") for u in range(self.q.n)])

    def arcs(self, arcs: DataFrame) -> DataFrame:
        """(q_edge, src, dst): arcs between full candidates."""
        return reduce(DataFrame.unionByName, [self.prune(e, relation(arcs, self.q, e).select("src", "dst")).select(F.lit(e).alias("q_edge"), "src", "dst") for e in range(self.q.m)])

    def path_counts(self, arcs: DataFrame, tree: Rooted | None = None) -> dict[int, int]:
        """Matches of each root path of a tree (this index's own, if none is given) within the candidates, level by level."""
        tree = tree or self.shape
        per = {tree.root: self.down[tree.root].vids().withColumn("cnt", F.lit(1).cast("long"))}
        for p, c in tree.edges():
            step = read_from(arcs, self.q, p, c).join(per[p].select(F.col("vid").alias("src"), "cnt"), "src").groupBy(F.col("dst").alias("vid")).agg(F.sum("cnt").alias("cnt"))
            per[c] = step.join(self.down[c].vids(), "vid", "left_semi")
        parts = [d.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("n")).select(F.lit(u).alias("u"), "n") for u, d in per.items()]
        return {r["u"]: r["n"] for r in reduce(DataFrame.unionByName, parts).collect()}

    def audit(self, matches: DataFrame, arcs: DataFrame) -> DataFrame:
        """Edges of matches that the index lacks: empty for a complete index."""
        kept = self.arcs(arcs)
        used = [matches.select(F.lit(e).alias("q_edge"), F.col(f"m{u}").alias("src"), F.col(f"m{w}").alias("dst")) for e, (u, w, _) in enumerate(self.q.edges)]
        return reduce(DataFrame.unionByName, used).distinct().join(kept, ["q_edge", "src", "dst"], "left_anti")


def _fits(q: Pattern, e: int, back: bool):
    """Whether an arc fits query edge e forwards or backwards."""
    u, w, label = q.edges[e]
    u, w = (w, u) if back else (u, w)
    keep = F.lit(True)
    for column, wanted in (("elabel", label), ("slabel", q.vlabels[u]), ("dlabel", q.vlabels[w])):
        if wanted is not None:
            keep = keep & (F.col(column) == wanted)
    return keep


def label_candidates(q: Pattern, arcs: DataFrame, vertices: DataFrame, level: str = "vertex") -> DataFrame:
    """Candidate counts by labels alone; at level ``edge`` every query edge needs one fitting incident arc as well."""
    parts = []
    for u in range(q.n):
        label = q.vlabels[u]
        c = (vertices if label is None else vertices.filter(F.col("vlabel") == label)).select("vid")
        if level == "edge":
            for w in q.neighbours(u):
                c = c.join(read_from(arcs, q, u, w).select(F.col("src").alias("vid")), "vid", "left_semi")
        parts.append(c.agg(F.count(F.lit(1)).alias("n_candidates")).select(F.lit(u).alias("u"), "n_candidates"))
    return reduce(DataFrame.unionByName, parts)
