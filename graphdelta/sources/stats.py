"""Graph statistics: sizes, labels, degrees, hops, cores."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdelta.pattern.model import Pattern
from graphdelta.plans.relations import fits
from graphdelta.sources.storage import cut



def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("degree"))


def graph_stats(edges: DataFrame) -> DataFrame:
    """One row: vertices with an edge, edges, edge labels, average and largest degree, share of the top label."""
    deg = degrees(edges).agg(F.count(F.lit(1)).alias("n_vertices"), F.max("degree").alias("max_degree"))
    labels = edges.groupBy("elabel").count().agg(F.count(F.lit(1)).alias("n_elabels"), F.max("count").alias("top"), F.sum("count").alias("n_edges"))
    one = deg.withColumn("k", F.lit(1)).join(labels.withColumn("k", F.lit(1)), "k")
    return one.select("n_vertices", "n_edges", "n_elabels", F.round(2 * F.col("n_edges") / F.col("n_vertices"), 4).alias("avg_degree"), "max_degree", F.round(F.col("top") / F.col("n_edges"), 4).alias("top_label_share"))


def label_histogram(edges: DataFrame) -> DataFrame:
    return edges.groupBy("elabel").agg(F.count(F.lit(1)).alias("n_edges"))


def degree_distribution(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("degree").agg(F.count(F.lit(1)).alias("n_vertices"))


def hub_topk(edges: DataFrame, k: int) -> DataFrame:
    return degrees(edges).orderBy(F.desc("degree"), "vid").limit(k)


def khop(arcs: DataFrame, start: DataFrame, hops: int) -> DataFrame:
    """(vid, hop) of all vertices within some hops of the start vertices."""
    steps = arcs.select("src", "dst").distinct()
    seen = start.select("vid").distinct().withColumn("hop", F.lit(0))
    front = seen
    for h in range(1, hops + 1):
        reached = front.select(F.col("vid").alias("src")).join(steps, "src").select(F.col("dst").alias("vid")).distinct()
        front = reached.join(seen, "vid", "left_anti").withColumn("hop", F.lit(h))
        seen = seen.unionByName(front)
    return seen


def core_numbers(edges: DataFrame, most_rounds: int | None = None) -> DataFrame:
    """(vid, core) by repeated h-index over neighbours, until nothing changes; rounds are cut by checkpoints.

    Bounds only fall, so this ends; with ``most_rounds`` it raises when they have not settled by then.
    """
    arcs = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    core = cut(degrees(edges).select("vid", F.col("degree").alias("core")))
    for _ in count() if most_rounds is None else range(most_rounds):
        near = arcs.join(core.select(F.col("vid").alias("dst"), "core"), "dst").groupBy("src", "core").agg(F.count(F.lit(1)).alias("c"))
        # h-index from how many neighbours have each core: a hub is one row a value, not one a neighbour
        above = near.withColumn("n", F.sum("c").over(Window.partitionBy("src").orderBy(F.desc("core"))))
        new = cut(above.groupBy("src").agg(F.max(F.least("n", "core")).alias("core")).select(F.col("src").alias("vid"), F.col("core").cast("long").alias("core")))
        changed = new.join(core.withColumnRenamed("core", "old"), "vid").filter("core != old").limit(1).count()
        core = new
        if not changed:
            return core
    raise RuntimeError("core numbers did not settle")


def relation_sizes(arcs: DataFrame, q: Pattern) -> list[int]:
    """Rows of every query relation, in one pass over the arcs."""
    row = arcs.agg(*[F.count(F.when(fits(q, e), 1)).alias(f"e{e}") for e in range(q.m)]).first()
    return [row[f"e{e}"] for e in range(q.m)]


def label_sizes(vertices: DataFrame, q: Pattern) -> list[int]:
    """Vertices that bear the label of every pattern vertex."""
    row = vertices.agg(*[F.count(F.when(F.lit(True) if label is None else F.col("vlabel") == label, 1)).alias(f"v{u}") for u, label in enumerate(q.vlabels)]).first()
    return [row[f"v{u}"] for u in range(q.n)]


