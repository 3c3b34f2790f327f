"""Pattern helpers for SQL: UDFs over pattern JSON, a UDTF of its edges, and a key for the subgraph of a match."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from graphdelta.pattern.model import from_json
from graphdelta.plans.orders import order_direct
from graphdelta.sources.graph import PropertyGraph


def subgraph_key(n: int) -> Column:
    """The same key for all automorphic images of a match: its sorted vertices."""
    return F.array_sort(F.array(*[F.col(f"m{u}") for u in range(n)]))


def distinct_subgraphs(matches: DataFrame, n: int) -> DataFrame:
    return matches.select(subgraph_key(n).alias("key")).distinct()


def match_count(sign: Column | str = "sign") -> Column:
    """Net number of matches of signed rows; an aggregate."""
    return F.coalesce(F.sum(sign), F.lit(0)).cast("long")


def geo_mean_speedup(ta: Column | str, tb: Column | str) -> Column:
    """Geometric mean over rows of tb over ta; an aggregate."""
    a, b = (F.col(t) if isinstance(t, str) else t for t in (ta, tb))
    return F.exp(F.avg(F.log(b / a)))


def relative_max(x: Column | str) -> Column:
    """Mean of a measure over its largest value in the group; an aggregate, 1 where nothing is greater than zero."""
    x = F.col(x) if isinstance(x, str) else x
    return F.when(F.max(x) > 0, F.avg(x) / F.max(x)).otherwise(F.lit(1.0))


@udtf(returnType="u int, w int, elabel string")
class PatternEdges:
    def eval(self, text: str):
        for u, w, label in from_json(text).edges:
            yield u, w, label


@udtf(returnType="pos int, u int")
class DirectOrder:
    def eval(self, text: str, x: int, y: int):
        yield from enumerate(order_direct(from_json(text), (x, y)))


def register(spark: SparkSession) -> None:
    """pattern_class, pattern_diameter, pattern_edges and direct_order for spark.sql."""
    spark.udf.register("pattern_class", F.udf(lambda text: text and from_json(text).density_class, "string", useArrow=True))
    spark.udf.register("pattern_diameter", F.udf(lambda text: text and from_json(text).diameter, "int", useArrow=True))
    spark.udtf.register("pattern_edges", PatternEdges)
    spark.udtf.register("direct_order", DirectOrder)


def create_views(g: PropertyGraph) -> None:
    """Views vertices, edges and arcs."""
    g.vertices.createOrReplaceTempView("vertices")
    g.edges.createOrReplaceTempView("edges")
    g.arcs().createOrReplaceTempView("arcs")
