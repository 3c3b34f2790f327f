"""The data graph as two tables, and its arcs."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdelta.schema import ARC_COLUMNS
from graphdelta.sources.storage import cut


@dataclass
class PropertyGraph:
    vertices: DataFrame
    edges: DataFrame

    def arcs(self) -> DataFrame:
        """Both directions of every edge, with the labels of both ends."""
        return arcs_of(self.edges, self.vertices)


def arcs_of(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Labels are joined once per edge and flipped with it; an edge without a known vertex is left out.

    Where the edges have a ``batch_id``, both arcs bear it.
    """
    own = [c for c in ("batch_id",) if c in edges.columns]
    label = lambda side, name: vertices.select(F.col("vid").alias(side), F.col("vlabel").alias(name))
    one = edges.select("src", "dst", "elabel", *own).join(label("src", "slabel"), "src").join(label("dst", "dlabel"), "dst").select(*ARC_COLUMNS, *own)
    two = one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel", F.col("dlabel").alias("slabel"), F.col("slabel").alias("dlabel"), *own)
    return one.unionByName(two)


def simple(rows: DataFrame) -> DataFrame:
    """Edges of any rows (src, dst, elabel, ts): no loops, least end first, the first by (ts, elabel) of a pair."""
    ordered = rows.filter("src != dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "elabel", "ts")
    first = ordered.groupBy("src", "dst").agg(F.min(F.struct("ts", "elabel")).alias("f"))
    return first.select("src", "dst", "f.elabel", "f.ts")


def numbered(rows: DataFrame, *keys: str) -> DataFrame:
    """The rows with ``n``, their place from 0 in the order of ``keys``, which must tell all rows apart.

    Rows are dealt by ranges and sorted apart from each other; only the counts of the ranges are added up in one place.
    """
    within = F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)
    placed = cut(rows.orderBy(*keys).select("*", F.spark_partition_id().alias("_part"), within.alias("_place")), "numbered")
    sizes = placed.groupBy("_part").agg(F.count(F.lit(1)).alias("_size"))
    before = sizes.select("_part", F.coalesce(F.sum("_size").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return placed.join(F.broadcast(before), "_part").withColumn("n", F.col("_place") + F.col("_before")).drop("_part", "_place", "_before")


def split_stream(edges: DataFrame, rate: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """Initial edges and the last part by (ts, src, dst) as the insert stream."""
    placed = numbered(edges, "ts", "src", "dst")
    keep = int(placed.count() * (1 - rate) + 1e-9)
    return placed.filter(F.col("n") < keep).drop("n"), placed.filter(F.col("n") >= keep).drop("n")


def split_hash(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """About a tenth of the edges, chosen by plain arithmetic on their ends, as the insert stream."""
    chosen = (F.col("src") * 31 + F.col("dst") * 17) % 10 == 0
    return edges.filter(~chosen), edges.filter(chosen)


def write_bucketed(arcs: DataFrame, name: str, buckets: int) -> None:
    """Arcs bucketed and sorted by their first end: joins on it then move the partial matches only."""
    arcs.write.bucketBy(buckets, "src").sortBy("src", "elabel", "dst").mode("overwrite").saveAsTable(name)


def read_edge_list(spark, path: str, kind: str = "csv") -> DataFrame:
    """Edges from CSV or JSON lines of src, dst, elabel, ts, made simple."""
    reader = spark.read.schema("src long, dst long, elabel string, ts timestamp")
    return simple(reader.csv(path, header=True) if kind == "csv" else reader.json(path))
