"""Streams of updates: one trigger is one batch, and state lives in tables written per batch."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.methods.state import MatchState, apply_batch, prepare
from graphdelta.pattern.model import Pattern
from graphdelta.sources.graph import PropertyGraph
from graphdelta.sources.updates import deletes, inserts, normalise

LOG = "op string, src long, dst long, elabel string, ts timestamp, batch_id int"
UPDATE = "seq long, op string, src long, dst long, elabel string, ts timestamp"
MARK = "top long, n_late long, batch_id int"
ACTIVITY = "key long, n long, first timestamp, last timestamp"


class Watermark:
    """Splits off the rows of a batch that lie more than ``delay`` seconds before the latest row of all earlier batches.

    The latest time and the count of late rows of every batch are written to a small table, so a replayed or restarted
    batch is split as it was the first time.  Rows without a time are never late.
    """

    def __init__(self, folder: str, delay: int):
        self.folder, self.delay = folder.rstrip("/"), delay

    def in_time(self, batch: DataFrame, batch_id: int) -> DataFrame:
        spark, at = batch.sparkSession, F.unix_micros("ts")
        top = self.marks(spark).filter(F.col("batch_id") < batch_id).agg(F.max("top")).first()[0] if batch_id else None
        late = F.lit(False) if top is None else F.coalesce(at < top - self.delay * 1_000_000, F.lit(False))
        batch.agg(F.max(at).alias("top"), F.count(F.when(late, 1)).alias("n_late")).write.mode("overwrite").parquet(f"{self.folder}/marks/batch_id={batch_id}")
        return batch.filter(~late)

    def marks(self, spark: SparkSession) -> DataFrame:
        """(top, n_late, batch_id) of every batch so far."""
        return spark.read.schema(MARK).parquet(f"{self.folder}/marks")


class StreamMatcher:
    """foreachBatch target: signed matches of every batch under ``out``/batch_id=...; the method's state is kept between triggers.

    The normalised edges of each batch are written beside its matches.  A replayed batch starts from the state before
    it and writes its folders anew; a restarted matcher makes its state from the first edges and the logged batches
    before the one that comes, so no match is reported twice.  With ``late``, updates more than so many seconds behind
    the latest one of earlier batches are counted (``watermark.marks``) and not applied.
    """

    def __init__(self, g: PropertyGraph, q: Pattern, folder: str, method: str = "direct_delta", semantics: str = "iso", late: int | None = None):
        self.folder, self.first = folder.rstrip("/"), (g, q, method, semantics)
        self.watermark = None if late is None else Watermark(self.folder, late)
        self.states: dict[int, MatchState] = {}

    def state_before(self, spark: SparkSession, batch_id: int) -> MatchState:
        if batch_id not in self.states:
            g, q, method, semantics = self.first
            if batch_id:
                log = spark.read.schema(LOG).parquet(f"{self.folder}/log").filter(F.col("batch_id") < batch_id)
                last = log.groupBy("src", "dst").agg(F.max(F.struct("batch_id", F.expr("op = '+'").alias("plus"), "elabel", "ts")).alias("x")).select("src", "dst", "x.plus", "x.elabel", "x.ts")
                kept = g.edges.join(last, ["src", "dst"], "left_anti").select("src", "dst", "elabel", "ts")
                g = PropertyGraph(g.vertices, kept.unionByName(last.filter("plus").select("src", "dst", "elabel", "ts")))
            self.states[batch_id] = prepare(g, q, method, semantics)
        return self.states[batch_id]

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        state = self.state_before(batch.sparkSession, batch_id)
        if self.watermark is not None:
            batch = self.watermark.in_time(batch, batch_id)
        edges = state.arcs.now().filter("src < dst").select("src", "dst", "elabel")
        minus, plus = normalise(batch, edges)
        done = deletes(minus).unionByName(inserts(plus))
        done.write.mode("overwrite").parquet(f"{self.folder}/log/batch_id={batch_id}")
        after, found = apply_batch(state, done)
        found.write.mode("overwrite").parquet(f"{self.folder}/out/batch_id={batch_id}")
        self.states = {batch_id: state, batch_id + 1: after}

    def run(self, stream: DataFrame) -> None:
        """Process all that the stream holds now and stop; a later call goes on from its checkpoint."""
        query = stream.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.folder}/checkpoint").trigger(availableNow=True).start()
        query.awaitTermination()

    def matches(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.folder}/out")


def file_updates(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Updates from a folder to which Parquet files are added; each trigger takes so many of them."""
    return spark.readStream.schema(UPDATE).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def window_counts(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events per window and label, tumbling or sliding, with a watermark when the input is a stream."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.window("ts", length, slide or length).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """Events per user session."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def temporal_wedge(first: DataFrame, second: DataFrame, within: str, late: str = "1 hour") -> DataFrame:
    """Two-edge paths a-b-c whose second edge follows the first in time; as a stream-stream join it appends."""
    one, two = first.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("ts").alias("t1")), second.select(F.col("src").alias("b2"), F.col("dst").alias("c"), F.col("ts").alias("t2"))
    if first.isStreaming:
        one, two = one.withWatermark("t1", late), two.withWatermark("t2", late)
    return one.join(two, (F.col("b") == F.col("b2")) & (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"interval {within}"))).select("a", "b", "c", "t1", "t2")


def activity(events: DataFrame, key: str) -> DataFrame:
    """Updates of (key, n, first, last): rows of every key and their time span, as state kept by key between triggers.

    A trigger's rows of a key pass in pieces and only the three numbers stay, whatever the key's share of the stream; keys or times
    that are null are left out.
    """

    def work(group, pieces, state):
        n, first, last = state.get if state.exists else (0, None, None)
        for part in pieces:
            n += len(part)
            low, high = part["ts"].min(), part["ts"].max()
            first, last = low if first is None else min(first, low), high if last is None else max(last, high)
        state.update((n, first, last))
        yield pd.DataFrame({"key": [group[0]], "n": [n], "first": [first], "last": [last]})

    rows = events.select(F.col(key).cast("long").alias("key"), "ts").dropna()
    return rows.groupBy("key").applyInPandasWithState(work, ACTIVITY, ACTIVITY.partition(", ")[2], "update", "NoTimeout")
