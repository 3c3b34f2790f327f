"""Per-row matching orders: each partial match takes next the vertex with fewest candidates.

All telescoped terms grow together: a row carries the number k of its term, and a relation row that belongs to the
batch counts for it only where the query edge comes before k.  Rows that have different vertices mapped are kept
apart by that set; the sets are connected parts of the pattern, so their number depends on the pattern alone.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.operators.extend import bound_edges, col, injective
from graphdelta.pattern.model import Pattern
from graphdelta.sources.storage import cut


def side(rels: dict[int, DataFrame], q: Pattern, e: int, u: int, x: int) -> DataFrame:
    src, dst = ("src", "dst") if q.edges[e][0] == u else ("dst", "src")
    return rels[e].select(F.col(src).alias(col(u)), F.col(dst).alias(col(x)), F.col("new").alias("_new"))


def allowed(e: int):
    return ~F.col("_new") | (F.col("k") > e)


def grow(rows: DataFrame, rels, q: Pattern, x: int, bound: list[int]) -> DataFrame:
    """Candidates of x for every row, before the injectivity check."""
    out = rows
    for i, (e, u) in enumerate(bound_edges(q, x, bound)):
        on = [col(u)] if i == 0 else [col(u), col(x)]
        out = out.join(side(rels, q, e, u, x), on).filter(allowed(e)).drop("_new")
    return out


def candidate_count(rows: DataFrame, rels, q: Pattern, x: int, bound: list[int], mode: str, name: str) -> DataFrame:
    """Adds the number of candidates of x: exact, or bounded by the smallest neighbourhood."""
    if mode == "exact":
        own = ["k", *[col(u) for u in bound]]
        counts = grow(rows.select(*own), rels, q, x, bound).groupBy(*own).agg(F.count(F.lit(1)).alias(name))
        return rows.join(counts, own, "left").withColumn(name, F.coalesce(name, F.lit(0)))
    low = None
    for e, u in bound_edges(q, x, bound):
        degree = side(rels, q, e, u, x).groupBy(col(u)).agg(F.count(F.lit(1)).alias("_all"), F.count(F.when(~F.col("_new"), 1)).alias("_old"))
        here = F.coalesce(F.when(F.col("k") > e, F.col("_all")).otherwise(F.col("_old")), F.lit(0))
        rows = rows.join(degree, col(u), "left").withColumn(name, here if low is None else F.least(F.col(name), here)).drop("_all", "_old")
        low = name
    return rows


def enumerate_adaptive(rels: dict[int, DataFrame], q: Pattern, semantics: str = "iso", mode: str = "bound", seen=None) -> DataFrame:
    """Matches of all terms by the least-candidates rule; rels have (src, dst, new); ``seen`` gets each depth's tables."""
    live: dict[frozenset, list[DataFrame]] = {}
    for k, (x, y, _) in enumerate(q.edges):
        seed = side(rels, q, k, x, y).filter("_new").select(F.lit(k).alias("k"), col(x), col(y))
        live.setdefault(frozenset((x, y)), []).append(injective(seed, y, [x], semantics))
    for depth in range(2, q.n):
        tables = {have: cut(reduce(DataFrame.unionByName, parts)) for have, parts in live.items()}
        if seen is not None:
            seen.append((depth, list(tables.values())))
        live = {}
        for have, rows in tables.items():
            bound = sorted(have)
            near = sorted({w for u in bound for w in q.neighbours(u)} - have)
            if len(near) == 1:
                steps = [(near[0], rows)]
            else:
                for x in near:
                    rows = candidate_count(rows, rels, q, x, bound, mode, f"_c{x}")
                low = F.least(*[f"_c{x}" for x in near])
                choice = F.coalesce(*[F.when(F.col(f"_c{x}") == low, F.lit(x)) for x in near])
                rows = cut(rows.withColumn("_next", choice).filter(low > 0).select("k", *[col(u) for u in bound], "_next"))
                steps = [(x, rows.filter(F.col("_next") == x).drop("_next")) for x in near]
            for x, part in steps:
                wide = injective(grow(part, rels, q, x, bound), x, bound, semantics)
                live.setdefault(have | {x}, []).append(wide.select("k", *[col(u) for u in sorted(have | {x})]))
    out = reduce(DataFrame.unionByName, [p for parts in live.values() for p in parts])
    if seen is not None:
        seen.append((q.n, [out]))
    return out.select(*[col(u) for u in range(q.n)])
