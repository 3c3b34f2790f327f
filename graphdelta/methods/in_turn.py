"""Batches of insertions in turn, all in one plan: every row carries the moment at which it arises.

With m query edges, an arc of batch i has the moment i * m + e in the relation of query edge e.  Telescoped term k of
batch i begins at the arcs of moment i * m + k and takes from all other relations what is earlier: earlier query edges
with the batch, later ones without it, and all batches before.  So the terms of all batches grow together, and none
sees more of the stream than it would if the batches were applied one after the other; the number of Spark jobs does
not depend on the number of batches.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.operators.extend import bound_edges, col, finish, injective
from graphdelta.pattern.model import Pattern
from graphdelta.pattern.shape import Rooted
from graphdelta.plans.orders import check_connected
from graphdelta.plans.relations import fits
from graphdelta.sources.storage import cut

#: The moment of arcs that are there before the first batch.
BEFORE = -(1 << 62)


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def timed(base: DataFrame, delta: DataFrame, q: Pattern) -> dict[int, DataFrame]:
    """Every query relation (src, dst, at): arcs of before, and those of the batches (with batch_id) at their moments."""
    out = {}
    for e in range(q.m):
        old = base.filter(fits(q, e)).select("src", "dst", F.lit(BEFORE).cast("long").alias("at"))
        out[e] = old.unionByName(delta.filter(fits(q, e)).select("src", "dst", (F.col("batch_id") * q.m + e).cast("long").alias("at")))
    return out


def batch_of(moment, q: Pattern):
    """Batch of a moment."""
    return F.expr(f"({moment} - pmod({moment}, {q.m}L)) div {q.m}L")


def batch_end(moment, q: Pattern):
    """First moment after the batch of a moment."""
    return F.expr(f"{moment} - pmod({moment}, {q.m}L) + {q.m}L")


def usable(q: Pattern, rel: DataFrame, now: bool = False):
    """Whether a relation row (at) may be taken by a row of moment t: it is earlier, or with ``now`` of that moment.

    Where an index gave the row a ``live`` moment, its ends are candidates once the row's batch is in the index.
    """
    there = F.col("_at") == F.col("t") if now else F.col("_at") < F.col("t")
    return there & (F.col("_live") < batch_end("t", q)) if "live" in rel.columns else there


def side(rel: DataFrame, q: Pattern, e: int, u: int, x: int) -> DataFrame:
    src, dst = ("src", "dst") if q.edges[e][0] == u else ("dst", "src")
    return rel.select(F.col(src).alias("_u"), F.col(dst).alias("_x"), F.col("at").alias("_at"), *[F.col(c).alias("_live") for c in ("live",) if c in rel.columns])


def grow(rows: DataFrame, rels: dict[int, DataFrame], q: Pattern, x: int, bound: list[int], now: int | None = None) -> DataFrame:
    """Candidates of x for every row (t and bound vertices), before the injectivity check; ``now``: the term's own edge."""
    (e, u), *others = bound_edges(q, x, bound)
    out = rows.join(side(rels[e], q, e, u, x), F.col(col(u)) == F.col("_u")).filter(usable(q, rels[e], e == now))
    out = out.select(*rows.columns, F.col("_x").alias(col(x)))
    for e2, u2 in others:
        near = side(rels[e2], q, e2, u2, x)
        out = out.join(near, (F.col(col(u2)) == F.col("_u")) & (F.col(col(x)) == F.col("_x")) & usable(q, rels[e2], e2 == now), "left_semi")
    return out


def seed(rel: DataFrame, q: Pattern, k: int, x: int, y: int, semantics: str) -> DataFrame:
    """(t and both ends) of the batches' arcs in the relation of query edge k."""
    rows = rel.filter(F.col("at") != BEFORE)
    if "live" in rel.columns:
        rows = rows.filter(F.col("live") < batch_end("at", q))
    src, dst = ("src", "dst") if q.edges[k][0] == x else ("dst", "src")
    return injective(rows.select(F.col("at").alias("t"), F.col(src).alias(col(x)), F.col(dst).alias(col(y))), y, [x], semantics)


def enumerate_in_turn(seeds: dict[int, DataFrame], rels: dict[int, DataFrame], orders: dict[int, list[int]], q: Pattern, semantics: str = "iso", keep=None, own: bool = False) -> DataFrame:
    """All matches (t and vertices) of the terms, which grow together by one vertex a round, each round one table.

    ``seeds[k]`` are rows over the first vertices of ``orders[k]``; ``keep(k, rows, x)`` may drop rows by the new vertex;
    ``own`` takes the edge k of term k at its moment, where the seed does not hold it.
    """
    for order in orders.values():
        check_connected(q, order)
    rows, start = dict(seeds), {k: len(df.columns) - 1 for k, df in seeds.items()}
    for i in range(min(start.values()), q.n):
        parts = []
        for k, order in orders.items():
            if start[k] <= i:
                x, bound = order[i], order[:i]
                rows[k] = injective(grow(rows[k], rels, q, x, bound, k if own else None), x, bound, semantics)
                rows[k] = rows[k] if keep is None else keep(k, rows[k], x)
            parts.append(rows[k].select(F.lit(k).alias("k"), "t", *[F.col(col(u)).alias(f"p{j}") for j, u in enumerate(order[: i + 1])]))
        table = cut(union(parts), "partials")
        rows = {k: table.filter(F.col("k") == k).select("t", *[F.col(f"p{j}").alias(col(u)) for j, u in enumerate(order[: i + 1])]) for k, order in orders.items()}
    return union([finish(df, q, ("t",)) for df in rows.values()])


def by_terms_in_turn(rels: dict[int, DataFrame], q: Pattern, order_of, semantics: str = "iso") -> DataFrame:
    """Terms of all batches under a rule that orders the vertices from each seed edge."""
    order = {k: order_of(k, x, y) for k, (x, y, _) in enumerate(q.edges)}
    seeds = {k: seed(rels[k], q, k, order[k][0], order[k][1], semantics) for k in order}
    return enumerate_in_turn(seeds, rels, order, q, semantics)


# ---------------------------------------------------------------- candidates by moment


@dataclass(frozen=True)
class Live:
    """From which moment on a vertex is a candidate of the index, were it kept batch by batch and query edge by query edge.

    ``down[u]`` has (vid, live) of full candidates; ``support[p, c]`` of vertices with a neighbour that is a full candidate of c.
    """

    down: dict[int, DataFrame]
    support: dict[tuple[int, int], DataFrame]
    labelled: dict[int, DataFrame]


def read_from(rels: dict[int, DataFrame], q: Pattern, p: int, c: int) -> DataFrame:
    """Relation of the edge between p and c as (src on p's side, dst on c's side, at)."""
    e = q.edge_between(p, c)
    return rels[e].select("src", "dst", "at") if q.edges[e][0] == p else rels[e].select(F.col("dst").alias("src"), F.col("src").alias("dst"), "at")


def lives(q: Pattern, shape: Rooted, rels: dict[int, DataFrame], vertices: DataFrame, top_down: bool = True) -> Live:
    """Insertions only ever add candidates, so one walk along the shape gives each vertex's first moment, for all batches."""

    def supported(arcs: DataFrame, near: str, far: str, flags: DataFrame) -> DataFrame:
        rows = arcs.join(flags.withColumnRenamed("vid", far), far)
        return cut(rows.groupBy(F.col(near).alias("vid")).agg(F.min(F.greatest("at", "live")).alias("live")), "live")

    def all_of(first: DataFrame, sides: list[DataFrame]) -> DataFrame:
        return reduce(lambda a, b: a.join(b.withColumnRenamed("live", "_l"), "vid").select("vid", F.greatest("live", "_l").alias("live")), sides, first)

    labelled = {}
    for u, label in enumerate(q.vlabels):
        mine = vertices if label is None else vertices.filter(F.col("vlabel") == label)
        labelled[u] = mine.select("vid", F.lit(BEFORE).cast("long").alias("live"))
    up: dict[int, DataFrame] = {}
    for u in shape.order:
        parents = shape.parents[u] if top_down else ()
        up[u] = all_of(labelled[u], [supported(read_from(rels, q, p, u), "dst", "src", up[p]) for p in parents])
    down: dict[int, DataFrame] = {}
    support: dict[tuple[int, int], DataFrame] = {}
    for u in reversed(shape.order):
        for c in shape.children[u]:
            support[u, c] = supported(read_from(rels, q, u, c), "src", "dst", down[c])
        down[u] = cut(all_of(up[u], [support[u, c] for c in shape.children[u]]), "live")
    return Live(down, support, labelled)


def pruned(rels: dict[int, DataFrame], q: Pattern, live: Live) -> dict[int, DataFrame]:
    """Every query relation between full candidates, with the moment from which both ends are."""
    parts = []
    for e, (u, w, _) in enumerate(q.edges):
        src = live.down[u].select(F.col("vid").alias("src"), F.col("live").alias("_s"))
        dst = live.down[w].select(F.col("vid").alias("dst"), F.col("live").alias("_d"))
        parts.append(rels[e].join(src, "src").join(dst, "dst").select(F.lit(e).alias("q_edge"), "src", "dst", "at", F.greatest("_s", "_d").alias("live")))
    every = cut(union(parts), "pruned")
    return {e: every.filter(F.col("q_edge") == e).drop("q_edge") for e in range(q.m)}


def candidate_bound(rows: DataFrame, rels: dict[int, DataFrame], q: Pattern, x: int, bound: list[int], name: str) -> DataFrame:
    """Adds the smallest neighbourhood of x's bound neighbours, each as of the row's moment."""
    low = None
    for e, u in bound_edges(q, x, bound):
        asked = rows.select("t", col(u)).distinct()
        steps = side(rels[e], q, e, u, x).groupBy("_u", "_at", "_live").agg(F.count(F.lit(1)).alias("_n"))
        degree = asked.join(steps, F.col(col(u)) == F.col("_u")).filter(usable(q, rels[e])).groupBy("t", col(u)).agg(F.sum("_n").alias("_n"))
        here = F.coalesce("_n", F.lit(0))
        rows = rows.join(degree, ["t", col(u)], "left").withColumn(name, here if low is None else F.least(F.col(name), here)).drop("_n")
        low = name
    return rows


def adaptive_in_turn(rels: dict[int, DataFrame], q: Pattern, semantics: str = "iso") -> DataFrame:
    """Matches (t and vertices) of all terms of all batches, each row taking next the vertex with fewest candidates."""
    live: dict[frozenset, list[DataFrame]] = {}
    for k, (x, y, _) in enumerate(q.edges):
        live.setdefault(frozenset((x, y)), []).append(seed(rels[k], q, k, x, y, semantics))
    for _ in range(2, q.n):
        tables = {have: cut(union(parts), "partials") for have, parts in live.items()}
        live = {}
        for have, rows in tables.items():
            bound = sorted(have)
            near = sorted({w for u in bound for w in q.neighbours(u)} - have)
            steps = [(near[0], rows)]
            if len(near) > 1:
                for x in near:
                    rows = candidate_bound(rows, rels, q, x, bound, f"_c{x}")
                low = F.least(*[f"_c{x}" for x in near])
                choice = F.coalesce(*[F.when(F.col(f"_c{x}") == low, F.lit(x)) for x in near])
                rows = cut(rows.withColumn("_next", choice).filter(low > 0).select("t", *[col(u) for u in bound], "_next"), "partials")
                steps = [(x, rows.filter(F.col("_next") == x).drop("_next")) for x in near]
            for x, part in steps:
                wide = injective(grow(part, rels, q, x, bound), x, bound, semantics)
                live.setdefault(have | {x}, []).append(wide.select("t", *[col(u) for u in sorted(have | {x})]))
    return finish(union([p for parts in live.values() for p in parts]), q, ("t",))


# ---------------------------------------------------------------- bottom-up index


def alive(rows: DataFrame, column: str, live: DataFrame) -> DataFrame:
    """The rows whose ``column`` is in a table (vid, live) at their moment, between the terms."""
    known = live.select(F.col("vid").alias("_v"), F.col("live").alias("_live"))
    return rows.join(known, F.col(column) == F.col("_v")).filter(F.col("_live") < F.col("t")).select(*rows.columns)


def local_in_turn(q: Pattern, tree: Rooted, rels: dict[int, DataFrame], live: Live, k: int) -> dict[int, DataFrame]:
    """Local candidates (t, vid) of term k of every batch: from the batch's edge k up to the root, what leads to it."""
    u, w, _ = q.edges[k]
    p, c = (u, w) if u in tree.parents[w] else (w, u)
    own = read_from(rels, q, p, c).filter(F.col("at") != BEFORE).select(F.col("at").alias("t"), "src", "dst")
    rows = alive(own, "dst", live.down[c])
    out: dict[int, DataFrame] = {}
    while True:
        vids = rows.select("t", F.col("src").alias("vid")).distinct()
        for table in [live.labelled[p], *[live.support[p, x] for x in tree.children[p] if x != c]]:
            vids = alive(vids, "vid", table)
        out[p] = cut(vids, "local")
        if not tree.parents[p]:
            return out
        p, c = tree.parents[p][0], p
        near = read_from(rels, q, p, c).select(F.col("src"), F.col("dst").alias("vid"), F.col("at").alias("_at"))
        rows = out[c].join(near, "vid").filter(F.col("_at") < F.col("t")).select("t", "src")


def bottomup_in_turn(q: Pattern, tree: Rooted, rels: dict[int, DataFrame], vertices: DataFrame, semantics: str = "iso") -> DataFrame:
    """Matches of all terms from the root down, over local candidates on the way to a batch and global ones elsewhere."""
    live = lives(q, tree, rels, vertices, top_down=False)
    local = {k: local_in_turn(q, tree, rels, live, k) for k in range(q.m)}

    def keep(k: int, rows: DataFrame, x: int) -> DataFrame:
        if x in local[k]:
            return rows.join(local[k][x].withColumnRenamed("vid", col(x)), ["t", col(x)], "left_semi").select(*rows.columns)
        return alive(rows, col(x), live.down[x])

    seeds = {k: local[k][tree.root].select("t", F.col("vid").alias(col(tree.root))) for k in local}
    return enumerate_in_turn(seeds, rels, {k: list(tree.order) for k in local}, q, semantics, keep, own=True)
