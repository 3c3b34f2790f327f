"""Patterns drawn from a graph: connected parts of it, thinned to a density class; each has a match by construction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.pattern.model import Pattern
from graphdelta.sources.storage import cut

#: Walks that are begun for every pattern asked for: not every part of a graph is dense enough.
TRIES = 4


def walks(arcs: DataFrame, size: int, count: int, seed: int) -> DataFrame:
    """(w, vids): ``count`` vertices chosen by hash, each grown by the neighbour that touches most of the part, ties by hash."""
    steps = arcs.select("src", "dst").distinct()
    first = steps.select("src").distinct().orderBy(F.xxhash64(F.lit(seed), "src"), "src").limit(count)
    rows = cut(first.select(F.col("src").alias("w"), F.array("src").alias("vids")), "walks")
    for _ in range(size - 1):
        near = rows.select("w", "vids", F.explode("vids").alias("src")).join(steps, "src").filter(~F.array_contains("vids", F.col("dst")))
        ranked = near.groupBy("w", "dst").agg(F.count(F.lit(1)).alias("ties"), F.first("vids").alias("vids"))
        best = ranked.groupBy("w").agg(F.max(F.struct("ties", F.xxhash64(F.lit(seed), "w", "dst").alias("h"), "dst", "vids")).alias("b"))
        rows = cut(best.select("w", F.concat("b.vids", F.array("b.dst")).alias("vids")), "walks")
    return rows


def thinned(n: int, pairs: list[tuple[int, int]], kind: str) -> list[tuple[int, int]] | None:
    """Edges of a connected part kept for a class: a spanning tree, up to three edges for two vertices, or all if more."""
    tree, seen = [], {0}
    while len(seen) < n:
        step = next(((u, w) for u, w in pairs if (u in seen) != (w in seen)), None)
        if step is None:
            return None
        tree.append(step)
        seen |= set(step)
    rest = [p for p in pairs if p not in tree]
    if kind == "tree":
        return sorted(tree)
    if kind == "sparse":
        return sorted(tree + rest[: max(0, 3 * n // 2 - len(tree))]) if rest else None
    return sorted(pairs) if 2 * len(pairs) > 3 * n else None


def sample_patterns(arcs: DataFrame, size: int, kind: str, count: int, seed: int = 1) -> list[Pattern]:
    """Up to ``count`` patterns of a size and class (tree, sparse, dense) with the labels of the graph's own parts."""
    rows = walks(arcs, size, count * TRIES, seed)
    place = rows.select("w", F.posexplode("vids").alias("i", "vid"))
    a, b = place.select("w", F.col("i").alias("u"), F.col("vid").alias("src")), place.select("w", F.col("i").alias("x"), F.col("vid").alias("dst"))
    inside = arcs.join(a, "src").join(b, ["w", "dst"]).filter("u < x").select("w", "u", "x", "elabel", "slabel", "dlabel")
    parts: dict[int, list] = {}
    for r in inside.orderBy("w", "u", "x").collect():  # count * TRIES parts of at most size^2 edges
        parts.setdefault(r["w"], []).append(r)
    out = []
    for w in sorted(parts):
        edges = {(r["u"], r["x"]): r for r in parts[w]}
        labels = {r["u"]: r["slabel"] for r in parts[w]} | {r["x"]: r["dlabel"] for r in parts[w]}
        kept = thinned(size, sorted(edges), kind) if len(labels) == size else None
        if kept and len(out) < count:
            out.append(Pattern(tuple(labels[i] for i in range(size)), tuple((u, x, edges[u, x]["elabel"]) for u, x in kept), f"{kind}{size}_{w}"))
    return [q for q in out if q.density_class == kind]
