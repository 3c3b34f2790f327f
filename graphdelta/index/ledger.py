"""Counts per vertex that outlive a batch: a base table and the changes since, folded together every few batches."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.sources.storage import cut

#: Change tables after which a ledger writes a new base.
COMPACT = 8


class Ledger:
    """(vid, n): what counts is n > 0.  Changes are signed counts; a batch reads only the vertices it touches."""

    def __init__(self, base: DataFrame, changes: tuple[DataFrame, ...] = ()):
        self.base, self.changes = base, changes

    def _rows(self) -> DataFrame:
        return reduce(DataFrame.unionByName, self.changes, self.base)

    @staticmethod
    def _summed(rows: DataFrame) -> DataFrame:
        return rows.groupBy("vid").agg(F.sum("n").alias("n")).filter("n > 0")

    def now(self) -> DataFrame:
        return self._summed(self._rows()) if self.changes else self.base

    def vids(self) -> DataFrame:
        return self.now().select("vid")

    def of(self, vids: DataFrame) -> DataFrame:
        """(vid) of the given vertices that count now.  Written small tables make this a scan without a shuffle of the base."""
        mine = self._rows().join(vids, "vid", "left_semi")
        return (self._summed(mine) if self.changes else mine).select("vid")

    def plus(self, change: DataFrame) -> Ledger:
        grown = Ledger(self.base, (*self.changes, change.select("vid", F.col("n").cast("long").alias("n"))))
        return Ledger(cut(grown.now(), "ledger")) if len(grown.changes) >= COMPACT else grown
