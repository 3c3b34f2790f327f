"""Query relations as filters over arcs, and the telescoped terms of a change."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.pattern.model import Pattern

#: Rows up to which the changed edges of a batch are broadcast; beyond it they are joined by shuffle.
MOST_BROADCAST = 1_000_000


def fits(q: Pattern, e: int):
    """Whether an arc fits query edge e in its direction u to w."""
    u, w, label = q.edges[e]
    keep = F.lit(True)
    for column, wanted in (("elabel", label), ("slabel", q.vlabels[u]), ("dlabel", q.vlabels[w])):
        if wanted is not None:
            keep = keep & (F.col(column) == wanted)
    return keep


def relation(arcs: DataFrame, q: Pattern, e: int) -> DataFrame:
    """Arcs (src, dst) that fit query edge e, with ``new`` where the arcs tell which belong to the batch."""
    return arcs.filter(fits(q, e)).select("src", "dst", *[c for c in ("new",) if c in arcs.columns])


def relations(arcs: DataFrame, q: Pattern) -> dict[int, DataFrame]:
    return {e: relation(arcs, q, e).select("src", "dst") for e in range(q.m)}


def directed(rel: DataFrame, forward: bool) -> DataFrame:
    return rel if forward else rel.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


@dataclass
class Change:
    """A batch of one sign: the arcs without an inserted batch, or with a deleted one, and the batch's own arcs.

    Both are written tables, so a term scans them with its labels pushed down; the batch's table is small and known to be.
    """

    base: DataFrame
    delta: DataFrame
    sign: int
    size: int | None = None

    @property
    def full(self) -> DataFrame:
        """Arcs with the batch."""
        return self.base.unionByName(self.delta) if self.sign > 0 else self.base

    @property
    def rest(self) -> DataFrame:
        """Arcs without the batch."""
        return self.base if self.sign > 0 else self.base.join(self.seed(self.delta.select("src", "dst")), ["src", "dst"], "left_anti").select(*self.base.columns)

    @property
    def after(self) -> DataFrame:
        """Arcs once the batch has happened."""
        return self.full if self.sign > 0 else self.rest

    @property
    def arcs(self) -> DataFrame:
        """All arcs, with ``new`` for those of the batch; a filter on it leaves one side of the union."""
        return self.rest.withColumn("new", F.lit(False)).unionByName(self.delta.withColumn("new", F.lit(True)))

    def count(self) -> int:
        """Arcs of the batch, two for each edge."""
        if self.size is None:
            self.size = self.delta.count()
        return self.size

    def seed(self, df: DataFrame) -> DataFrame:
        """Broadcast what comes from the batch while the batch is small."""
        return F.broadcast(df) if self.count() <= MOST_BROADCAST else df


def flagged(change: Change, q: Pattern) -> dict[int, DataFrame]:
    """Every query relation once, with the batch's rows marked."""
    arcs = change.arcs
    return {e: relation(arcs, q, e) for e in range(q.m)}


def term(rels: dict[int, DataFrame], k: int) -> dict[int, DataFrame]:
    """Relations of term k: earlier edges with the batch, edge k the batch alone, later edges without it."""
    return {e: (r if e < k else r.filter("new") if e == k else r.filter("not new")).select("src", "dst") for e, r in rels.items()}
