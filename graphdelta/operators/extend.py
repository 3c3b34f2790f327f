"""Vertex-at-a-time enumeration: grow partial matches by one pattern vertex through joins.

A partial match is a row of long columns m0, m1, ...; a step joins one relation of a bound neighbour, then filters
by the relations of the other bound neighbours, then drops repeated data vertices unless homomorphisms are wanted.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.pattern.model import Pattern
from graphdelta.plans.orders import check_connected
from graphdelta.sources.storage import cut


def col(u: int) -> str:
    return f"m{u}"


def bound_edges(q: Pattern, x: int, bound: list[int]) -> list[tuple[int, int]]:
    """(edge, bound neighbour) of a vertex, in the order of the bound part."""
    return [(q.edge_between(u, x), u) for u in bound if q.edge_between(u, x) is not None]


def towards(rels: dict[int, DataFrame], q: Pattern, e: int, u: int, x: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """Relation of edge e read from u to x, columns named for the partial match."""
    rel = rels[e]
    src, dst = ("src", "dst") if q.edges[e][0] == u else ("dst", "src")
    return rel.select(*keys, F.col(src).alias(col(u)), F.col(dst).alias(col(x)))


def injective(df: DataFrame, x: int, bound: list[int], semantics: str) -> DataFrame:
    """Drop rows that map x to a data vertex already taken, as soon as x is there."""
    if semantics == "hom":
        return df
    return df.filter(reduce(lambda a, b: a & b, [F.col(col(x)) != F.col(col(u)) for u in bound]))


def expand(partial: DataFrame, rels, q: Pattern, x: int, bound: list[int], keys=()) -> DataFrame:
    """Candidates of x by its bound neighbours, before the injectivity check."""
    (e, u), *others = bound_edges(q, x, bound)
    out = partial.join(towards(rels, q, e, u, x, keys), [*keys, col(u)])
    for e2, u2 in others:
        out = out.join(towards(rels, q, e2, u2, x, keys), [*keys, col(u2), col(x)], "left_semi")
    return out


def expand_least(partial: DataFrame, rels, q: Pattern, x: int, bound: list[int], keys=()) -> DataFrame:
    """The same candidates, each row proposed by its bound neighbour of fewest relation rows, the others verifying."""
    ends = bound_edges(q, x, bound)
    if len(ends) == 1:
        return expand(partial, rels, q, x, bound, keys)
    sized = partial
    for i, (e, u) in enumerate(ends):
        degree = towards(rels, q, e, u, x, keys).groupBy(*keys, col(u)).agg(F.count(F.lit(1)).alias(f"_d{i}"))
        sized = sized.join(degree, [*keys, col(u)])  # without any neighbour there is no candidate
    low = F.least(*[F.col(f"_d{i}") for i in range(len(ends))])
    first = F.coalesce(*[F.when(F.col(f"_d{i}") == low, F.lit(i)) for i in range(len(ends))])
    sized = sized.withColumn("_by", first).drop(*[f"_d{i}" for i in range(len(ends))])
    parts = []
    for i, (e, u) in enumerate(ends):
        out = sized.filter(F.col("_by") == i).drop("_by").join(towards(rels, q, e, u, x, keys), [*keys, col(u)])
        for j, (e2, u2) in enumerate(ends):
            if j != i:
                out = out.join(towards(rels, q, e2, u2, x, keys), [*keys, col(u2), col(x)], "left_semi")
        parts.append(out)
    return reduce(DataFrame.unionByName, parts)


def finish(df: DataFrame, q: Pattern, keys=()) -> DataFrame:
    return df.select(*keys, *[col(u) for u in range(q.n)])


def enumerate_from(seed: DataFrame, rels, q: Pattern, order: list[int], semantics: str = "iso", strategy: str = "first", keys=(), start: int = 2) -> DataFrame:
    """All matches that grow from partial matches over the first ``start`` vertices of a connected order."""
    check_connected(q, order)
    grow = expand_least if strategy == "least" else expand
    out = seed
    for i in range(start, q.n):
        out = injective(grow(out, rels, q, order[i], order[:i], keys), order[i], order[:i], semantics)
    return finish(out, q, keys)


def enumerate_terms(seeds: dict[int, DataFrame], rels, orders: dict[int, list[int]], q: Pattern, semantics: str = "iso", strategy: str = "first", keep=None, seen=None) -> DataFrame:
    """All matches of several telescoped terms, which grow together by one vertex a round.

    ``seeds`` are partial matches over the first vertices of ``orders``; ``rels[k]`` the relations of term k.  Every
    round's partial matches are written as one table: the next round knows how small they are and scans the
    relations against them instead of shuffling both.  ``keep(k, rows, x)`` may drop rows by the new vertex x;
    ``seen(depth, k, rows, grown)`` gets what a round started from and what it found.
    """
    grow = expand_least if strategy == "least" else expand
    for order in orders.values():
        check_connected(q, order)
    named = lambda df, k, i: df.select(F.lit(k).alias("k"), *[F.col(col(u)).alias(f"p{j}") for j, u in enumerate(orders[k][:i])])
    rows = dict(seeds)
    start = {k: len(df.columns) for k, df in seeds.items()}
    for i in range(min(start.values(), default=q.n), q.n):
        parts = []
        for k, order in orders.items():
            if start[k] > i:
                parts.append(named(rows[k], k, i + 1))
                continue
            x, bound = order[i], order[:i]
            grown = injective(grow(rows[k], rels[k], q, x, bound), x, bound, semantics)
            if seen is not None:
                seen(i, k, rows[k], grown)
            parts.append(named(grown, k, i + 1))
        last = i == q.n - 1
        table = reduce(DataFrame.unionByName, parts)
        if not last or keep is not None:
            table = cut(table, "partials")
        rows = {}
        for k, order in orders.items():
            mine = table.filter(F.col("k") == k).select(*[F.col(f"p{j}").alias(col(u)) for j, u in enumerate(order[: i + 1])])
            rows[k] = mine if keep is None or start[k] > i else keep(k, mine, order[i])
        if last and keep is None:
            return reduce(DataFrame.unionByName, [finish(p.select(*[F.col(f"p{j}").alias(col(u)) for j, u in enumerate(o)]), q) for p, o in zip(parts, orders.values(), strict=True)])
    return reduce(DataFrame.unionByName, [finish(df, q) for df in rows.values()])


def first_vertex(rels, q: Pattern, u: int) -> DataFrame:
    """Values of a vertex that all its relations share."""
    ends = [towards(rels, q, q.edge_between(u, w), u, w).select(col(u)) for w in q.neighbours(u)]
    return reduce(lambda a, b: a.join(b, col(u), "left_semi"), ends[1:], ends[0]).distinct()


def match(rels, q: Pattern, order: list[int], semantics: str = "iso", strategy: str = "first", keys=(), limit: int | None = None) -> DataFrame:
    """All matches over the relations, one vertex at a time along the order."""
    e = q.edge_between(order[0], order[1])
    if e is None:
        raise ValueError(f"{order} does not begin with an edge")
    seed = towards(rels, q, e, order[0], order[1], keys)
    if not keys and q.n > 2:
        seed = seed.join(first_vertex(rels, q, order[0]), col(order[0]), "left_semi")
    out = enumerate_from(injective(seed, order[1], order[:1], semantics), rels, q, order, semantics, strategy, keys)
    return out if limit is None else out.limit(limit)


def edge_join(rels, q: Pattern, edge_order: list[int], semantics: str = "iso") -> DataFrame:
    """All matches one edge at a time."""
    out, bound = None, []
    for e in edge_order:
        u, w, _ = q.edges[e]
        side = towards(rels, q, e, u, w)
        shared = [v for v in (u, w) if v in bound]
        out = side if out is None else out.join(side, [col(v) for v in shared])
        for v in (u, w):
            if v not in bound:
                out = injective(out, v, bound, semantics) if bound else out
                bound.append(v)
    return finish(out, q)
