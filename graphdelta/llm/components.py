"""Connected components of a link table, by alternating star contractions.

Each round is two aggregations and two joins over the remaining edges; edges live in the shared folder between
rounds, never on the driver.  A vertex with very many links costs a partial aggregate; its edges meet one row in a
join, as a stream in one task unless adaptive execution splits the partition, and are never held together in memory.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.llm.common import dropped, saved

MOST_ROUNDS = 60


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction of edges (a, b): neighbours of a vertex move to the least one around it."""
    if large:
        near = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        near = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = near.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    met = near.join(low, "a")
    moved = met.filter(F.col("b") > F.col("a")) if large else met
    out = moved.select(F.col("b").alias("a"), F.col("m").alias("b"))
    if not large:
        out = out.unionByName(low.select("a", F.col("m").alias("b")))
    return out.filter(F.col("a") != F.col("b")).distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0)), F.coalesce(F.sum(F.xxhash64("a", "b") % 1000003), F.lit(0))).first())


def components(links: DataFrame) -> DataFrame:
    """(id, component) of every vertex of ``links`` (a, b); component is the least id reachable."""
    edges = saved(links.filter(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    before = _mark(edges)
    if before[0]:
        for _ in range(MOST_ROUNDS):
            after = saved(_star(_star(edges, True), False), "edges")
            dropped(edges)
            edges, now = after, _mark(after)
            if now == before:
                break
            before = now
        else:
            raise RuntimeError("components did not settle")
    low = edges.select(F.col("a").alias("id"), F.col("b").alias("component"))
    return low.unionByName(edges.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())
