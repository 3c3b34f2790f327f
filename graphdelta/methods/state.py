"""What a method keeps between batches: prepare once, then apply one batch after the other.

Arcs are a base table with the batches since as small tables, deleted arcs as tombstones; indexes are ledgers, join
trees are lists of tables.  All of them are folded into new base tables every few batches, so a batch never rewrites
what it does not touch.  A state is a value: applying a batch gives a new one, and the old one stays readable.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.index.candidates import CandidateIndex
from graphdelta.index.ledger import COMPACT
from graphdelta.methods import matchers as M
from graphdelta.methods.in_turn import adaptive_in_turn, batch_of, bottomup_in_turn, by_terms_in_turn, lives, pruned, timed
from graphdelta.pattern.model import Pattern, UnsupportedUpdate
from graphdelta.pattern.shape import Rooted
from graphdelta.plans import orders
from graphdelta.plans.relations import Change
from graphdelta.sources.graph import PropertyGraph, arcs_of
from graphdelta.sources.stats import relation_sizes
from graphdelta.sources.storage import cut
from graphdelta.sources.updates import arrivals, normalise

INDEX_OF = {"tree_index": "tree", "dag_index": "dag", "bottomup_index": "bottomup", "direct_dag": "dag", "tree_dag": "dag", "bottomup_dag": "dag"}


@dataclass(frozen=True)
class ArcStore:
    """Arcs by version: rows of version v that no tombstone of a later version names."""

    base: DataFrame
    came: tuple[DataFrame, ...] = ()
    gone: tuple[DataFrame, ...] = ()
    version: int = 0

    @staticmethod
    def of(g: PropertyGraph) -> ArcStore:
        return ArcStore(cut(g.arcs(), "arcs"))

    def now(self) -> DataFrame:
        at = lambda df, v: df.withColumn("_v", F.lit(v))
        rows = reduce(DataFrame.unionByName, self.came, at(self.base, 0))
        if self.gone:
            dead = reduce(DataFrame.unionByName, self.gone).groupBy("src", "dst").agg(F.max("_g").alias("_g"))
            rows = rows.join(dead, ["src", "dst"], "left").filter(F.col("_g").isNull() | (F.col("_v") >= F.col("_g"))).drop("_g")
        return rows.drop("_v").select(*self.base.columns)

    def plus(self, change: Change) -> ArcStore:
        v = self.version + 1
        came = (*self.came, change.delta.withColumn("_v", F.lit(v))) if change.sign > 0 else self.came
        gone = (*self.gone, change.delta.select("src", "dst", F.lit(v).alias("_g"))) if change.sign < 0 else self.gone
        grown = ArcStore(self.base, came, gone, v)
        return ArcStore(cut(grown.now(), "arcs")) if len(came) + len(gone) >= COMPACT else grown


@dataclass(frozen=True)
class MatchState:
    """A pattern's method on a graph as of now: arcs, the method's index or join tree, and the orders chosen offline."""

    q: Pattern
    method: str
    semantics: str
    vertices: DataFrame
    arcs: ArcStore
    index: CandidateIndex | None = None
    tree: M.JoinTree | None = None
    chosen: tuple[Rooted, list[int]] | None = None


def prepare(g: PropertyGraph, q: Pattern, method: str = "direct_delta", semantics: str = "iso") -> MatchState:
    """The offline phase: write the arcs, build the index or the join tree, choose what is chosen beforehand."""
    vertices, arcs = cut(g.vertices, "vertices"), ArcStore.of(g)
    index = M.build_index(INDEX_OF[method], q, arcs.now(), vertices) if method in INDEX_OF else None
    tree = M.JoinTree(q, relation_sizes(arcs.now(), q), semantics).build(arcs.now()) if method == "cached_join_tree" else None
    chosen = None
    if method in ("tree_index", "tree_dag"):
        chosen = M.path_order(index, arcs.now(), tree=None if method == "tree_index" else M.shape_for("tree", q, arcs.now(), vertices))
    return MatchState(q, method, semantics, vertices, arcs, index, tree, chosen)


def apply_change(state: MatchState, change: Change, limit: int | None = None, enumerate_matches: bool = True) -> tuple[MatchState, DataFrame | None]:
    """The state after a batch of one sign, and its signed matches (none if only the index is to follow)."""
    M.check_support(state.method, change, limit)
    q, semantics, method = state.q, state.semantics, state.method
    after = replace(state, arcs=state.arcs.plus(change))
    if method == "cached_join_tree":
        found, tree = state.tree.insert(change)
        return replace(after, tree=tree), found
    if method == "bottomup_index":
        if not enumerate_matches:
            return replace(after, index=state.index.updated(change)), None
        found, index = M.bottomup_step(state.index, change, semantics, limit)
        return replace(after, index=index), found
    if state.index is None:
        return after, M.run_method(method, change, q, state.vertices, semantics, limit) if enumerate_matches else None
    if method == "dag_index":
        found = lambda ix: M.adaptive(ix, change, q, semantics, limit=limit)
    else:
        by = {
            "direct_dag": lambda k, x, y: orders.order_direct(q, (x, y)),
            "bottomup_dag": lambda k, x, y: orders.seeded(q, list(M.shape_for("bottomup", q, change.base, state.vertices).order), (x, y)),
        }.get(method) or M.tree_orders(q, *state.chosen)
        found = lambda ix: M.by_terms(change, q, by, semantics, limit=limit, keep=M.checked(ix))
    out, index = M.step_index(state.index, change, found if enumerate_matches else lambda ix: None)
    return replace(after, index=index), out


def changes_of(state: MatchState, batch: DataFrame) -> tuple[Change, Change]:
    """A mixed batch (op, src, dst, elabel, ts and perhaps seq) as its deletions and, after them, its insertions."""
    arcs = state.arcs.now()
    minus, plus = normalise(batch, _edges(state))
    delta = lambda edges: cut(arcs_of(edges, state.vertices), "delta")
    gone = Change(arcs, delta(minus), -1)
    return gone, Change(state.arcs.plus(gone).now() if gone.count() else arcs, delta(plus), 1)


def apply_batch(state: MatchState, batch: DataFrame, limit: int | None = None, enumerate_matches: bool = True) -> tuple[MatchState, DataFrame | None]:
    """The state after a mixed batch, and its signed matches: deletions first, then insertions, empty parts left out."""
    parts = []
    for change in changes_of(state, batch):
        if change.count():
            state, found = apply_change(state, change, limit, enumerate_matches)
            parts += [found] if found is not None else []
    if not enumerate_matches:
        return state, None
    if not parts:
        spark = batch.sparkSession
        parts = [spark.createDataFrame([], ", ".join([f"m{u} long" for u in range(state.q.n)] + ["sign int"]))]
    return state, reduce(DataFrame.unionByName, parts)


def _edges(state: MatchState) -> DataFrame:
    return state.arcs.now().filter("src < dst").select("src", "dst", "elabel")


def _apply_insertions(state: MatchState, stream: DataFrame) -> tuple[MatchState, DataFrame]:
    """The state after batches of insertions, and their matches (batch_id, vertices, sign) as of each batch's turn."""
    q, semantics, method = state.q, state.semantics, state.method
    arcs = state.arcs.now()
    delta = cut(arcs_of(arrivals(stream, _edges(state)), state.vertices), "delta")
    change = Change(arcs, delta.drop("batch_id"), 1)
    M.check_support(method, change)
    after = replace(state, arcs=state.arcs.plus(change))
    if method == "cached_join_tree":
        found, tree = state.tree.insert(Change(arcs, delta, 1, change.size))
        return replace(after, tree=tree), found
    rels = timed(arcs, delta, q)
    if state.index is not None:
        after = replace(after, index=state.index.updated(change))
    if method == "bottomup_index":
        found = bottomup_in_turn(q, state.index.shape, rels, state.vertices, semantics)
    else:
        if state.index is not None:
            rels = pruned(rels, q, lives(q, state.index.shape, rels, state.vertices))
        if method == "dag_index":
            found = adaptive_in_turn(rels, q, semantics)
        elif state.chosen is not None:
            found = by_terms_in_turn(rels, q, M.tree_orders(q, *state.chosen), semantics)
        else:
            found = by_terms_in_turn(rels, q, lambda k, x, y: orders.order_direct(q, (x, y)), semantics)
    return after, found.select(batch_of("t", q).alias("batch_id"), *[f"m{u}" for u in range(q.n)], F.lit(1).cast("int").alias("sign"))


#: Methods whose batches of insertions run in one plan; the others take one batch after the other.
TOGETHER = ("direct_delta", "cached_join_tree", "direct_dag", "tree_index", "tree_dag", "bottomup_index", "dag_index")


def apply_batches(state: MatchState, stream: DataFrame) -> tuple[MatchState, DataFrame]:
    """The state after the batches of a stream (batch_id, op, src, dst, elabel, ts and perhaps seq) in the order of their
    ids, and all their signed matches with ``batch_id``: what ``apply_batch`` gives for one batch after the other.

    Batches of insertions that follow each other run in one plan; a batch with a deletion is applied by itself.
    """
    stream, q, parts = cut(stream, "stream"), state.q, []
    alone = stream if state.method not in TOGETHER else stream.filter("op = '-'")
    ids = sorted(r[0] for r in alone.select("batch_id").distinct().collect())
    for low, i in zip([None, *ids], [*ids, None], strict=True):
        if state.method in TOGETHER:
            run_of = stream.filter((F.lit(True) if low is None else F.col("batch_id") > low) & (F.lit(True) if i is None else F.col("batch_id") < i))
            if not run_of.isEmpty():
                state, found = _apply_insertions(state, run_of)
                parts.append(found)
        if i is not None:
            state, found = apply_batch(state, stream.filter(F.col("batch_id") == i).drop("batch_id"))
            parts.append(cut(found.select(F.lit(i).cast("long").alias("batch_id"), *[f"m{u}" for u in range(q.n)], "sign"), "found"))
    if not parts:
        parts = [stream.sparkSession.createDataFrame([], ", ".join(["batch_id long", *[f"m{u} long" for u in range(q.n)], "sign int"]))]
    return state, reduce(DataFrame.unionByName, parts)


def maintained(result: DataFrame, signed: DataFrame) -> DataFrame:
    """A stored result brought up to date by signed matches; what a batch took away and brought back stays."""
    cols = [c for c in signed.columns if c != "sign"]
    net = signed.groupBy(*cols).agg(F.sum("sign").alias("sign")).filter("sign != 0")
    return result.select(*cols).join(net.filter("sign < 0"), cols, "left_anti").unionByName(net.filter("sign > 0").select(*cols))


def run(state: MatchState, batches: list[DataFrame], enumerate_matches: bool = True, time_limit: float | None = None) -> tuple[MatchState, list[dict]]:
    """Apply batches in turn; one report a batch: seconds of index upkeep and of enumeration, matches, status.

    A batch over the time limit ends the run as ``unsolved``.  Reading and normalising the batch, which is the update of
    the data graph, is not counted.
    """
    import time

    reports = []
    for i, batch in enumerate(batches):
        t_index = t_enum = 0.0
        n = 0
        for change in changes_of(state, batch):
            if not change.count():
                continue
            began = time.monotonic()
            state, found = apply_change(state, change, enumerate_matches=enumerate_matches)
            t_index += time.monotonic() - began
            if found is not None:
                began = time.monotonic()
                n += found.count()
                t_enum += time.monotonic() - began
        late = time_limit is not None and t_index + t_enum > time_limit
        reports.append({"batch": i, "t_index": t_index, "t_enum": t_enum, "response_time": t_index + t_enum, "results": n, "status": "unsolved" if late else "solved"})
        if late:
            break
    return state, reports


__all__ = ["ArcStore", "MatchState", "UnsupportedUpdate", "apply_batch", "apply_batches", "apply_change", "changes_of", "maintained", "prepare", "run"]
