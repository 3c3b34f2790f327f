"""Relational operations around matches: optional edges, time-bounded wedges, labels as of a time, attributes, maps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphdelta.operators.extend import col


def optional(matches: DataFrame, rel: DataFrame, u: int, x: int) -> DataFrame:
    """Matches with a further vertex x next to u where the relation (src, dst) has one, else null."""
    return matches.join(rel.select(F.col("src").alias(col(u)), F.col("dst").alias(col(x))), col(u), "left")


def interval_wedge(arcs: DataFrame, seconds: int) -> DataFrame:
    """Two arcs out of one vertex whose times lie at most ``seconds`` apart: (mid, a, b), a < b.

    Times are dealt into slices of that length; a slice meets itself and its two neighbours, so the join is an equi join.
    """
    arcs = arcs.withColumn("ts", F.unix_micros(F.col("ts").cast("timestamp")))
    slice_of = F.floor(F.col("ts") / (seconds * 1_000_000))
    left = arcs.select(F.col("src").alias("mid"), F.col("dst").alias("a"), F.col("ts").alias("t1"), F.explode(F.array(slice_of - 1, slice_of, slice_of + 1)).alias("slice"))
    right = arcs.select(F.col("src").alias("mid"), F.col("dst").alias("b"), F.col("ts").alias("t2"), slice_of.alias("slice"))
    apart = F.abs(F.col("t1") - F.col("t2"))
    return left.join(right, ["mid", "slice"]).filter((F.col("a") < F.col("b")) & (apart <= seconds * 1_000_000)).select("mid", "a", "b")


def label_as_of(edges: DataFrame, labels: DataFrame, end: str = "src") -> DataFrame:
    """Edges with ``label``, the last label (vid, ts, seq, label) of one end at or before the edge's time; null before the first."""
    one = edges.select(F.col(end).alias("vid"), "ts", F.lit(1).alias("kind"), F.lit(None).cast("long").alias("seq"), F.lit(None).cast("string").alias("label"), F.struct("src", "dst").alias("e"))
    two = labels.select("vid", "ts", F.lit(0).alias("kind"), F.col("seq").cast("long").alias("seq"), "label", F.lit(None).cast("struct<src:bigint,dst:bigint>").alias("e"))
    past = Window.partitionBy("vid").orderBy("ts", "kind", "seq").rowsBetween(Window.unboundedPreceding, 0)
    return one.unionByName(two).withColumn("label", F.last("label", ignorenulls=True).over(past)).filter("kind = 1").select("e.src", "e.dst", "label")


def with_attributes(matches: DataFrame, u: int, attributes: DataFrame, where: Column) -> DataFrame:
    """Matches whose vertex u has a row (vid, ...) of attributes that satisfies a predicate."""
    return matches.join(attributes.filter(where).select(F.col("vid").alias(col(u))), col(u), "left_semi").select(*matches.columns)


def as_map(matches: DataFrame, n: int) -> DataFrame:
    """One map a match, from pattern vertex to data vertex."""
    return matches.select(F.map_from_arrays(F.array(*[F.lit(u) for u in range(n)]), F.array(*[F.col(col(u)) for u in range(n)])).alias("m"))


def adjacency(arcs: DataFrame) -> DataFrame:
    """(src, nbrs): sorted neighbours.  A list is as long as its vertex's degree; hubs belong in ``arcs``."""
    return arcs.groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("nbrs"))


def common_neighbours(edges: DataFrame, arcs: DataFrame) -> DataFrame:
    """(src, dst, n): neighbours that both ends of an edge share, by intersecting sorted lists."""
    lists = adjacency(arcs)
    both = edges.select("src", "dst").join(lists.withColumnRenamed("nbrs", "x"), "src").join(lists.select(F.col("src").alias("dst"), F.col("nbrs").alias("y")), "dst")
    return both.select("src", "dst", F.size(F.array_intersect("x", "y")).cast("long").alias("n"))
