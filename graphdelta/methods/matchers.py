"""Signed matches of one batch, by every method.

All take a ``Change`` (arcs with, of and without the batch) and a pattern, and return match columns plus sign.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.index.candidates import CandidateIndex, as_vid, both, read_from
from graphdelta.index.ledger import COMPACT
from graphdelta.operators.adaptive import enumerate_adaptive
from graphdelta.operators.extend import col, edge_join, enumerate_terms, finish, injective, match, towards
from graphdelta.pattern.model import Pattern, UnsupportedPattern, UnsupportedUpdate
from graphdelta.pattern.shape import Rooted, rooted_dag, rooted_tree, spanning_tree
from graphdelta.plans import orders
from graphdelta.plans.relations import Change, fits, flagged, relation, relations, term
from graphdelta.sources.graph import numbered as numbered_rows
from graphdelta.sources.stats import label_sizes, relation_sizes
from graphdelta.sources.storage import cut


def signed(df: DataFrame, sign: int) -> DataFrame:
    return df.withColumn("sign", F.lit(sign).cast("int"))


def difference(q: Pattern, before: DataFrame, after: DataFrame) -> DataFrame:
    """Signed difference of two match sets."""
    cols = [col(u) for u in range(q.n)]
    return signed(after.join(before, cols, "left_anti"), 1).unionByName(signed(before.join(after, cols, "left_anti"), -1)).select(*cols, "sign")


def full_recompute(change: Change, q: Pattern, semantics: str = "iso") -> DataFrame:
    """Match before, match after, difference."""
    order = orders.any_connected(q)
    with_batch, without = (match(relations(a, q), q, order, semantics) for a in (change.full, change.rest))
    return difference(q, without, with_batch) if change.sign > 0 else difference(q, with_batch, without)


def local_recompute(change: Change, q: Pattern, semantics: str = "iso", serialise: bool = False) -> DataFrame:
    """Recompute in the neighbourhood of each changed edge, one edge after the other.

    The neighbourhood of an edge is what walks along the pattern reach from its ends, for each query edge that it may be the
    image of: it lies within the pattern's diameter of both ends and holds every match that uses the edge.

    A batch needs ``serialise``: its edges get numbers, edge i sees the batch's edges before it, and all edges run in
    one plan whose rows carry the number.
    """
    once = change.delta.filter("src < dst").select("src", "dst", "elabel", "slabel", "dlabel")
    if not serialise and once.count() > 1:
        raise UnsupportedUpdate("takes one edge at a time; serialise=True replays a batch edge by edge")
    numbered = cut(numbered_rows(once, "src", "dst").withColumnRenamed("n", "i"), "changed")  # any fixed order of replay gives the same net change
    back = numbered.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel", F.col("dlabel").alias("slabel"), F.col("slabel").alias("dlabel"), "i")
    first = F.lit(None).cast("long")
    changed = numbered.unionByName(back)
    arcs = change.rest.withColumn("since", first).unionByName(changed.withColumnRenamed("i", "since"))
    alive = F.col("since").isNull() | (F.col("since") <= F.col("i"))

    def around(k: int) -> dict[int, DataFrame]:
        """(i, vid) that pattern vertices may be mapped to when edge i is the image of query edge k, either way round."""
        u, w, _ = q.edges[k]
        own = changed.filter(fits(q, k))
        near = {x: cut(own.select("i", F.col(end).alias("vid")).distinct(), "near") for x, end in ((u, "src"), (w, "dst"))}
        for x in orders.order_direct(q, (u, w))[2:]:
            reached = []
            for p in (p for p in q.neighbours(x) if p in near):
                e = q.edge_between(p, x)
                src, dst = ("src", "dst") if q.edges[e][0] == p else ("dst", "src")
                steps = arcs.filter(fits(q, e)).select(F.col(src).alias("vid"), F.col(dst).alias("next"), "since")
                reached.append(near[p].join(steps, "vid").filter(alive).select("i", F.col("next").alias("vid")))
            near[x] = cut(reduce(lambda a, b: a.join(b, ["i", "vid"], "left_semi"), reached).distinct(), "near")
        return near

    parts = []
    for near in map(around, range(q.m)):
        for e, (u, w, _) in enumerate(q.edges):
            src, dst = near[u].withColumnRenamed("vid", "src"), near[w].withColumnRenamed("vid", "dst")
            rows = arcs.filter(fits(q, e)).select("src", "dst", "since").join(src, "src").filter(alive).join(dst, ["i", "dst"], "left_semi")
            parts.append(rows.select(F.lit(e).alias("q_edge"), "i", "src", "dst", "since"))
    held = cut(reduce(DataFrame.unionByName, parts).distinct(), "held")
    order = orders.any_connected(q)

    def found(local: DataFrame) -> DataFrame:
        rels = {}
        for e in range(q.m):
            rels[e] = local.filter(F.col("q_edge") == e).select("i", "src", "dst")
        return match(rels, q, order, semantics, keys=("i",))

    cols = [col(u) for u in range(q.n)]
    here = held.filter(F.coalesce(F.col("since") != F.col("i"), F.lit(True)))
    return signed(found(held).join(found(here), ["i", *cols], "left_anti").select(*cols), change.sign)


def _seed(change: Change, rels, q: Pattern, k: int, x: int, y: int, semantics: str) -> DataFrame:
    return change.seed(injective(towards(rels, q, k, x, y), y, [x], semantics))


def direct_delta(change: Change, q: Pattern, semantics: str = "iso", strategy: str = "first", rels=None, limit: int | None = None) -> DataFrame:
    """Telescoped terms straight on the graph, each seeded by the batch."""
    return by_terms(change, q, lambda k, x, y: orders.order_direct(q, (x, y)), semantics, rels, strategy, limit)


def by_terms(change: Change, q: Pattern, order_of, semantics: str, rels=None, strategy: str = "first", limit: int | None = None, keep=None) -> DataFrame:
    """Union of all terms under a rule that orders the vertices from each seed edge.

    With a limit the terms run one after the other until there are enough matches; the later ones never start.
    """
    marked = flagged(change, q) if rels is None else rels
    own = {k: term(marked, k) for k in range(q.m)}
    order = {k: order_of(k, x, y) for k, (x, y, _) in enumerate(q.edges)}
    seeds = {k: _seed(change, own[k], q, k, order[k][0], order[k][1], semantics) for k in own}
    if keep is not None:
        seeds = {k: keep(k, keep(k, df, order[k][0]), order[k][1]) for k, df in seeds.items()}
    if limit is None:
        return signed(enumerate_terms(seeds, own, order, q, semantics, strategy, keep), change.sign)
    parts, have = [], 0
    for k in own:
        parts.append(cut(enumerate_terms({k: seeds[k]}, own, {k: order[k]}, q, semantics, strategy, keep).limit(limit - have), "found"))
        have += parts[-1].count()
        if have >= limit:
            break
    return signed(reduce(DataFrame.unionByName, parts), change.sign)


class JoinTree:
    """Left-deep tree over the query edges that keeps every partial result as tables; takes insertions only."""

    def __init__(self, q: Pattern, size: list[int], semantics: str = "iso"):
        self.q, self.semantics, self.order = q, semantics, orders.order_edges(q, size)
        self.nodes: list[tuple[DataFrame, ...]] = []
        self.leaves: list[tuple[DataFrame, ...]] = []

    def _side(self, arcs: DataFrame, j: int) -> DataFrame:
        e = self.order[j]
        u, w, _ = self.q.edges[e]
        at = tuple(c for c in ("batch_id",) if c in arcs.columns)
        return towards({e: arcs.filter(fits(self.q, e)).select("src", "dst", *at)}, self.q, e, u, w, at)

    def _join(self, left: DataFrame, side: DataFrame, j: int) -> DataFrame:
        bound = list(dict.fromkeys(v for e in self.order[:j] for v in self.q.edges[e][:2]))
        u, w, _ = self.q.edges[self.order[j]]
        both_at = "batch_id" in left.columns and "batch_id" in side.columns
        out = left.join(side.withColumnRenamed("batch_id", "_at") if both_at else side, [col(v) for v in (u, w) if v in bound])
        if both_at:  # what two batches give together is there with the later one
            out = out.withColumn("batch_id", F.greatest("batch_id", "_at")).drop("_at")
        for v in (u, w):
            if v not in bound:
                out = injective(out, v, bound, self.semantics)
        return out

    @staticmethod
    def _whole(tables: tuple[DataFrame, ...]) -> DataFrame:
        return reduce(DataFrame.unionByName, tables)

    @staticmethod
    def _appended(tables: tuple[DataFrame, ...], new: DataFrame) -> tuple[DataFrame, ...]:
        grown = (*tables, new)
        return (cut(JoinTree._whole(grown), "node"),) if len(grown) > COMPACT else grown

    def build(self, arcs: DataFrame) -> JoinTree:
        self.leaves = [(cut(self._side(arcs, j), "leaf"),) for j in range(self.q.m)]
        u, w, _ = self.q.edges[self.order[0]]
        self.nodes = [(cut(injective(self.leaves[0][0], w, [u], self.semantics), "node"),)]
        for j in range(1, self.q.m):
            self.nodes.append((cut(self._join(self.nodes[-1][0], self.leaves[j][0], j), "node"),))
        return self

    def insert(self, change: Change) -> tuple[DataFrame, JoinTree]:
        """Signed matches of the batch, and the tree with all its partial results appended.

        Where the batch's arcs have a ``batch_id`` they are several batches in turn, and each partial result gets the
        batch that completes it.
        """
        if change.sign < 0:
            raise UnsupportedUpdate("the join tree takes no deletion")
        after = JoinTree(self.q, [0] * self.q.m, self.semantics)
        after.order = self.order
        u, w, _ = self.q.edges[self.order[0]]
        new = [cut(self._side(change.delta, j), "leaf") for j in range(self.q.m)]
        after.leaves = [self._appended(old, d.drop("batch_id")) for old, d in zip(self.leaves, new, strict=True)]
        grown = cut(injective(new[0], w, [u], self.semantics), "node")
        after.nodes = [self._appended(self.nodes[0], grown.drop("batch_id"))]
        keys = tuple(c for c in ("batch_id",) if c in change.delta.columns)
        for j in range(1, self.q.m):
            if keys:
                step = self._join(grown, new[j], j).unionByName(self._join(grown, self._whole(self.leaves[j]), j))
            else:
                step = self._join(grown, self._whole(after.leaves[j]), j)
            step = step.unionByName(self._join(self._whole(self.nodes[j - 1]), change.seed(new[j]), j))
            grown = cut(step, "node")
            after.nodes.append(self._appended(self.nodes[j], grown.drop("batch_id")))
        return signed(finish(grown, self.q, keys), 1), after


def cached_join_tree(change: Change, q: Pattern, semantics: str = "iso") -> DataFrame:
    return JoinTree(q, relation_sizes(change.rest, q), semantics).build(change.rest).insert(change)[0]


def shape_for(index: str, q: Pattern, arcs: DataFrame, vertices: DataFrame) -> Rooted:
    if index == "tree":
        return spanning_tree(q, relation_sizes(arcs, q), label_sizes(vertices, q))
    if index == "dag":
        return rooted_dag(q)
    if not q.is_tree:
        raise UnsupportedPattern("the bottom-up index takes tree patterns only")
    return rooted_tree(q)


def build_index(index: str, q: Pattern, arcs: DataFrame, vertices: DataFrame) -> CandidateIndex:
    """One of tree, dag, bottomup."""
    return CandidateIndex.build(q, shape_for(index, q, arcs, vertices), arcs, vertices, top_down=index != "bottomup")


def step_index(ix: CandidateIndex, change: Change, found) -> tuple[DataFrame, CandidateIndex]:
    """Matches by ``found(index)`` and the index after the batch: an insertion updates it first, a deletion last."""
    after = ix.updated(change)
    return found(after if change.sign > 0 else ix), after


def first_index(index: str, change: Change, q: Pattern, vertices: DataFrame, state: CandidateIndex | None) -> CandidateIndex:
    return state or build_index(index, q, change.base, vertices)


def current_index(index: str, change: Change, q: Pattern, vertices: DataFrame, state: CandidateIndex | None = None) -> CandidateIndex:
    """The index under which a batch is enumerated: after an insertion, before a deletion."""
    return step_index(first_index(index, change, q, vertices, state), change, lambda ix: ix)[0]


def checked(ix: CandidateIndex):
    """Keeps the partial matches whose new vertex is a full candidate."""
    return lambda k, rows, x: ix.keep(rows, col(x), x)


def path_order(ix: CandidateIndex, arcs: DataFrame, rule: str = "min", tree: Rooted | None = None) -> tuple[Rooted, list[int]]:
    """A spanning tree and the path-count order over an index's candidates."""
    tree = tree or ix.shape
    return tree, orders.order_paths(tree, ix.path_counts(arcs, tree), rule)


def tree_orders(q: Pattern, tree: Rooted, order: list[int]):
    deep = {u: len(tree.path_up(u)) for u in tree.order}
    return lambda k, x, y: orders.order_tree_seeded(q, tree, order, (x, y) if deep[x] <= deep[y] else (y, x))


def tree_index(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", rule: str = "min", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Spanning-tree candidates under path-count orders seeded at the batch."""
    ix = current_index("tree", change, q, vertices, state)
    return by_terms(change, q, tree_orders(q, *path_order(ix, change.full, rule)), semantics, limit=limit, keep=checked(ix))


def dag_index(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", mode: str = "bound", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Candidates over all query edges, each row taking next the vertex with fewest candidates."""
    return adaptive(current_index("dag", change, q, vertices, state), change, q, semantics, mode, limit)


def adaptive(ix: CandidateIndex, change: Change, q: Pattern, semantics: str = "iso", mode: str = "bound", limit: int | None = None) -> DataFrame:
    out = signed(enumerate_adaptive(ix.pruned(change), q, semantics, mode), change.sign)
    return out if limit is None else out.limit(limit)


def local_sets(ix: CandidateIndex, change: Change, k: int, rels: dict[int, DataFrame]) -> dict[int, DataFrame]:
    """Local candidates of term k, written: on the way from the batch's edge k up to the root, what leads to the batch.

    ``ix`` is the bottom-up index between the terms: earlier query edges with the batch, edge k and later ones without.
    """
    q, tree = ix.q, ix.shape
    u, w, _ = q.edges[k]
    p, c = (u, w) if u in tree.parents[w] else (w, u)
    batch = read_from(change.delta, q, p, c)
    rows = batch.join(ix.down[c].of(as_vid(batch, "dst").distinct()).withColumnRenamed("vid", "dst"), "dst", "left_semi")
    out: dict[int, DataFrame] = {}
    while True:
        vids = cut(as_vid(rows, "src").distinct(), "local")
        out[p] = both([vids, ix.labelled(p), *[ix.n_down[p, x].of(vids) for x in tree.children[p] if x != c]])
        if not tree.parents[p]:
            return out
        p, c = tree.parents[p][0], p
        e = q.edge_between(p, c)
        rel = rels[e] if q.edges[e][0] == p else rels[e].select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        rows = rel.join(out[c].withColumnRenamed("vid", "dst"), "dst", "left_semi")


def bottomup_term(ix: CandidateIndex, change: Change, k: int, semantics: str = "iso", seen=None) -> DataFrame:
    """Matches of term k from the root down, over local candidates on the way to the batch and global ones elsewhere."""
    q, tree = ix.q, ix.shape
    rels = term(flagged(change, q), k)
    local = local_sets(ix, change, k, rels)
    order = list(tree.order)

    def keep(_, rows, x):
        return rows.join(local[x].withColumnRenamed("vid", col(x)), col(x), "left_semi").select(*rows.columns) if x in local else ix.keep(rows, col(x), x)

    seed = local[tree.root].select(F.col("vid").alias(col(tree.root)))
    return enumerate_terms({k: seed}, {k: rels}, {k: order}, q, semantics, keep=keep, seen=seen)


def bottomup_step(ix: CandidateIndex, change: Change, semantics: str = "iso", limit: int | None = None, seen=None) -> tuple[DataFrame, CandidateIndex]:
    """Signed matches of a batch and the global bottom-up index after it, every term's share merged in its turn.

    Term k sees earlier query edges with the batch and later ones without it, in the index as in the relations; so under
    homomorphism every partial match leads to a match.  A deletion takes the terms from the last to the first.
    """
    parts, have = [], 0
    for k in range(ix.q.m) if change.sign > 0 else reversed(range(ix.q.m)):
        if change.sign < 0:
            ix_k = ix.updated(change, k)  # without edge k's batch arcs, which the term's seed brings back
        else:
            ix_k = ix
        if limit is None:
            parts.append(bottomup_term(ix_k, change, k, semantics, seen))
        elif have < limit:
            parts.append(cut(bottomup_term(ix_k, change, k, semantics, seen).limit(limit - have), "found"))
            have += parts[-1].count()
        ix = ix_k if change.sign < 0 else ix.updated(change, k)
    return signed(reduce(DataFrame.unionByName, parts), change.sign), ix


def bottomup_index(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Bottom-up candidates with a local index for each term, enumerated from the root down; tree patterns only."""
    return bottomup_step(first_index("bottomup", change, q, vertices, state), change, semantics, limit)[0]


def direct_dag(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Orders of the direct method over the DAG's candidates."""
    ix = current_index("dag", change, q, vertices, state)
    return by_terms(change, q, lambda k, x, y: orders.order_direct(q, (x, y)), semantics, limit=limit, keep=checked(ix))


def tree_dag(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Path-count orders over the DAG's candidates."""
    ix = current_index("dag", change, q, vertices, state)
    tree = shape_for("tree", q, change.full, vertices)
    return by_terms(change, q, tree_orders(q, *path_order(ix, change.full, tree=tree)), semantics, limit=limit, keep=checked(ix))


def bottomup_dag(change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", limit: int | None = None, state: CandidateIndex | None = None) -> DataFrame:
    """Depth-first orders over the DAG's candidates; tree patterns only."""
    tree = shape_for("bottomup", q, change.rest, vertices)
    ix = current_index("dag", change, q, vertices, state)
    return by_terms(change, q, lambda k, x, y: orders.seeded(q, list(tree.order), (x, y)), semantics, limit=limit, keep=checked(ix))


def static_snapshot(first: DataFrame, last: DataFrame, q: Pattern, semantics: str = "iso") -> DataFrame:
    """Net change between two snapshots, each matched once under a globally chosen order."""
    order = orders.order_static(q, relation_sizes(last, q))
    return difference(q, *(match(relations(a, q), q, order, semantics) for a in (first, last)))


def edge_delta(change: Change, q: Pattern, semantics: str = "iso") -> DataFrame:
    """Terms by edge-at-a-time joins, each begun by the batch."""
    parts = []
    for k in range(q.m):
        rels = term(flagged(change, q), k)
        rels[k] = change.seed(rels[k])
        sizes = [1] * q.m
        sizes[k] = 0
        parts.append(edge_join(rels, q, orders.order_edges(q, sizes), semantics))
    return signed(reduce(DataFrame.unionByName, parts), change.sign)


def count_tree_hom(q: Pattern, arcs: DataFrame, vertices: DataFrame, root: int = 0) -> DataFrame:
    """Number of homomorphisms of a tree pattern, by counting up the tree; no match is listed."""
    tree = rooted_tree(q, root)
    ways: dict[int, DataFrame] = {}
    for u in reversed(tree.order):
        label = q.vlabels[u]
        own = (vertices if label is None else vertices.filter(F.col("vlabel") == label)).select("vid", F.lit(1).cast("long").alias("n"))
        for c in tree.children[u]:
            up = read_from(arcs, q, u, c).join(ways[c].select(F.col("vid").alias("dst"), F.col("n").alias("k")), "dst").groupBy(F.col("src").alias("vid")).agg(F.sum("k").alias("k"))
            own = own.join(up, "vid").select("vid", (F.col("n") * F.col("k")).alias("n"))
        ways[u] = own
    return ways[tree.root].agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_matches"))


#: What each method takes as published: edge insertion, edge deletion, vertex insertion, vertex deletion, relabelling, native batches, early stop.
SUPPORT = {
    "local_recompute": (True, True, True, True, True, False, False),
    "direct_delta": (True, True, True, True, True, True, True),
    "cached_join_tree": (True, False, True, False, False, False, False),
    "bottomup_index": (True, True, True, True, True, True, True),
    "tree_index": (True, True, True, True, True, False, True),
    "dag_index": (True, True, True, True, True, False, True),
}


def check_support(name: str, change: Change, limit: int | None = None, batch_mode: str = "native") -> None:
    """Raise for what a method does not take.

    Batches of several edges are an extension for the methods that take one edge at a time as published; ``batch_mode``
    ``"serial"`` refuses them.
    """
    _, delete, *_, batch, early = SUPPORT.get(name, (True,) * 7)
    if change.sign < 0 and not delete:
        raise UnsupportedUpdate(f"{name} takes no deletion")
    if limit is not None and not early:
        raise UnsupportedUpdate(f"{name} cannot stop early")
    if batch_mode == "serial" and not batch and change.count() > 2:
        raise UnsupportedUpdate(f"{name} takes one edge at a time; batch_mode='native' takes a batch as a whole")


def run_method(name: str, change: Change, q: Pattern, vertices: DataFrame, semantics: str = "iso", limit: int | None = None, batch_mode: str = "native") -> DataFrame:
    """Any method by name, for one batch."""
    check_support(name, change, limit, batch_mode)
    plain = {"full_recompute": full_recompute, "cached_join_tree": cached_join_tree, "edge_delta": edge_delta}
    if name in plain:
        return plain[name](change, q, semantics)
    if name == "direct_delta":
        return direct_delta(change, q, semantics, limit=limit)
    if name == "local_recompute":
        return local_recompute(change, q, semantics, serialise=batch_mode == "native")
    indexed = {"tree_index": tree_index, "dag_index": dag_index, "bottomup_index": bottomup_index, "direct_dag": direct_dag, "tree_dag": tree_dag, "bottomup_dag": bottomup_dag}
    return indexed[name](change, q, vertices, semantics, limit=limit)


METHODS = ["full_recompute", "local_recompute", "direct_delta", "cached_join_tree", "tree_index", "dag_index", "bottomup_index", "direct_dag", "tree_dag", "bottomup_dag", "edge_delta"]
