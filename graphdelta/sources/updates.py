"""Update batches: normalising, applying, vertex and label updates, sliding windows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.plans.relations import Change
from graphdelta.sources.graph import PropertyGraph, arcs_of, numbered
from graphdelta.sources.storage import cut

EDGE = ["src", "dst", "elabel", "ts"]


def inserts(edges: DataFrame) -> DataFrame:
    return edges.select(F.lit("+").alias("op"), *EDGE)


def deletes(edges: DataFrame) -> DataFrame:
    return edges.select(F.lit("-").alias("op"), *EDGE)


def normalise(batch: DataFrame, edges: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(deleted, inserted) edges of a mixed batch.

    Loops go and ends are ordered.  Of the operations on one edge and label the last by seq counts (by ts where there is
    no seq; a deletion before an insertion of the same time).  Against the current edges, inserting what is there and
    deleting what is not has no effect; a pair that keeps its edge takes no second one, and of two labels that a batch
    inserts for one pair the first by (ts, label) stays.  Without the current edges every last operation is taken.
    """
    order = "seq" if "seq" in batch.columns else "ts"
    ends = batch.filter("src != dst").select("op", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "elabel", "ts", F.col(order).alias("o"))
    last = ends.groupBy("src", "dst", "elabel").agg(F.max(F.struct("o", F.expr("op = '+'").alias("plus"), "ts")).alias("x")).select("src", "dst", "elabel", "x.ts", "x.plus")
    minus, plus = last.filter("not plus").select(*EDGE), last.filter("plus").select(*EDGE)
    if edges is None:
        return minus, plus
    key = ["src", "dst", "elabel"]
    minus = minus.join(edges.select(*key), key, "left_semi")
    kept = edges.join(minus.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst")
    plus = plus.join(kept, ["src", "dst"], "left_anti")
    first = plus.groupBy("src", "dst").agg(F.min(F.struct("ts", "elabel")).alias("f")).select("src", "dst", "f.elabel", "f.ts")
    return minus.select(*EDGE), first.select(*EDGE)


def arrivals(stream: DataFrame, edges: DataFrame) -> DataFrame:
    """Edges that batches of insertions (batch_id, op, src, dst, elabel, ts and perhaps seq) add, each with its first batch.

    The same as ``normalise`` for each batch against the edges there by then: a pair that has an edge takes no second one.
    """
    order = "seq" if "seq" in stream.columns else "ts"
    ends = stream.filter("src != dst").select("batch_id", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "elabel", "ts", F.col(order).alias("o"))
    last = ends.groupBy("batch_id", "src", "dst", "elabel").agg(F.max(F.struct("o", "ts")).alias("x")).select("batch_id", "src", "dst", "elabel", "x.ts")
    fresh = last.join(edges.select("src", "dst"), ["src", "dst"], "left_anti")
    return fresh.groupBy("src", "dst").agg(F.min(F.struct("batch_id", "ts", "elabel")).alias("f")).select("src", "dst", "f.elabel", "f.ts", "f.batch_id")


def insertion(g: PropertyGraph, new: DataFrame) -> Change:
    """Change from a graph to the graph with new edges; its arcs and the batch's are written once."""
    return Change(cut(g.arcs(), "arcs"), cut(arcs_of(new, g.vertices), "delta"), 1)


def deletion(g: PropertyGraph, gone: DataFrame) -> Change:
    """Change from a graph to the graph without some of its edges."""
    mine = g.edges.join(gone.select("src", "dst").distinct(), ["src", "dst"], "left_semi")
    return Change(cut(g.arcs(), "arcs"), cut(arcs_of(mine, g.vertices), "delta"), -1)


def applied(g: PropertyGraph, minus: DataFrame, plus: DataFrame) -> PropertyGraph:
    rest = g.edges.join(minus.select("src", "dst"), ["src", "dst"], "left_anti")
    return PropertyGraph(g.vertices, rest.select(*EDGE).unionByName(plus.select(*EDGE)))


def mixed(g: PropertyGraph, batch: DataFrame) -> tuple[Change, Change, PropertyGraph]:
    """Deletions first, then insertions, and the graph after both."""
    minus, plus = normalise(batch, g.edges)
    first = deletion(g, minus)
    between = applied(g, minus, plus.limit(0))
    return first, insertion(between, plus), applied(g, minus, plus)


def vertex_delete(g: PropertyGraph, vids: DataFrame) -> DataFrame:
    """Deletions of all edges of some vertices."""
    touch = g.edges.join(vids.select(F.col("vid").alias("src")), "src", "left_semi").unionByName(g.edges.join(vids.select(F.col("vid").alias("dst")), "dst", "left_semi").select(*g.edges.columns))
    return deletes(touch.distinct())


def relabel(edges: DataFrame, new_label: DataFrame) -> DataFrame:
    """Delete each edge whose label changes and insert it with the new one (src, dst, new)."""
    both = edges.join(new_label, ["src", "dst"]).filter(F.col("new") != F.col("elabel"))
    return deletes(both).unionByName(inserts(both.select("src", "dst", F.col("new").alias("elabel"), "ts")))


def window_by_time(edges: DataFrame, now, length: str) -> DataFrame:
    """Edges alive in a sliding time window that ends at ``now``."""
    end = F.lit(now).cast("timestamp")
    return edges.filter((F.col("ts") <= end) & (F.col("ts") > end - F.expr(f"interval {length}")))


def slide(edges: DataFrame, then, now, length: str) -> DataFrame:
    """The batch that moves a time window on: edges that leave it are deletions, those that enter it insertions."""
    before, after = window_by_time(edges, then, length), window_by_time(edges, now, length)
    key = ["src", "dst"]
    return deletes(before.join(after.select(*key), key, "left_anti")).unionByName(inserts(after.join(before.select(*key), key, "left_anti")))


def window_by_count(edges: DataFrame, most: int) -> DataFrame:
    """The last ``most`` edges by (ts, src, dst)."""
    return edges.orderBy(F.desc("ts"), F.desc("src"), F.desc("dst")).limit(most)


def batches(edges: DataFrame, size: int) -> DataFrame:
    """Insert stream with seq, the place by (ts, src, dst) from 0, cut into batches of ``size`` edges."""
    placed = numbered(edges.select(*EDGE), "ts", "src", "dst").withColumnRenamed("n", "seq")
    return placed.select(F.floor(F.col("seq") / size).cast("long").alias("batch_id"), "seq", F.lit("+").alias("op"), *EDGE)
