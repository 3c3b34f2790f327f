"""Data graphs built from the relational, event and vector tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdelta.sources.graph import PropertyGraph, simple

#: Typed vertex ids are 10 * key + code.
CODES = {"customer": 0, "order": 1, "part": 2, "supplier": 3, "nation": 4, "region": 5}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _consecutive(spark: SparkSession, sf_dir: str, label: str) -> PropertyGraph:
    """Parts on consecutive lines of an order, over all orders, from the earliest date on; labels are a column of part."""
    lines = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_linenumber").alias("n"), F.col("l_partkey").alias("p")).distinct()
    dated = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), F.col("o_orderdate").alias("ts"))
    pairs = lines.join(lines.select("k", (F.col("n") - 1).alias("n"), F.col("p").alias("q")), ["k", "n"]).filter("p != q").join(dated, "k")
    ends = pairs.groupBy(F.least("p", "q").alias("src"), F.greatest("p", "q").alias("dst")).agg(F.min("ts").alias("ts"))
    edges = ends.select("src", "dst", F.lit("co").alias("elabel"), "ts")
    return PropertyGraph(read(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.col(label).alias("vlabel")), edges)


def copurchase(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Parts ordered one after the other; vertex labels are part types."""
    return _consecutive(spark, sf_dir, "p_type")


def cobrand(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Parts ordered one after the other; vertex labels are brands."""
    return _consecutive(spark, sf_dir, "p_brand")


def previous_user(events: DataFrame) -> DataFrame:
    """Each event with the user of the event before it by (ts, event_id), over all events.

    Hours are ordered apart from each other; the last user of each hour reaches the first event of the next one
    through a table with one row an hour, so no task orders all events.
    """
    hour = F.date_trunc("hour", "ts")
    rows = events.select("event_id", "ts", "user_id", "event_type", "value", hour.alias("hour"))
    inside = rows.withColumn("before", F.lag("user_id").over(Window.partitionBy("hour").orderBy("ts", "event_id")))
    ends = rows.groupBy("hour").agg(F.max(F.struct("ts", "event_id", "user_id")).alias("last"))
    carried = ends.select("hour", F.lag("last.user_id").over(Window.orderBy("hour")).alias("carried"))
    return inside.join(carried, "hour").select("event_id", "ts", "user_id", "event_type", "value", F.coalesce("before", "carried").alias("previous"))


def interaction(spark: SparkSession, sf_dir: str, label=None) -> PropertyGraph:
    """Users that act one after the other; edge labels are event types, all vertices are alike."""
    rows = previous_user(read(spark, sf_dir, "events")).filter(F.col("previous").isNotNull() & (F.col("previous") != F.col("user_id")))
    ends = rows.select(F.least("user_id", "previous").alias("src"), F.greatest("user_id", "previous").alias("dst"), (F.col("event_type") if label is None else label).alias("elabel"), "ts", "event_id")
    first = ends.groupBy("src", "dst").agg(F.min(F.struct("ts", "event_id", "elabel")).alias("f"))
    edges = first.select("src", "dst", "f.elabel", "f.ts")
    users = read(spark, sf_dir, "events").select(F.col("user_id").alias("vid")).distinct().withColumn("vlabel", F.lit("user"))
    return PropertyGraph(users, edges)


def interaction_skew(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """The same graph with most edges under one label."""
    return interaction(spark, sf_dir, label=F.when(F.col("value") < 61.5, "main").otherwise(F.col("event_type")))


def commerce(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Customers, orders, parts, suppliers, nations and regions; edge labels tell kind and state."""
    get = lambda name: read(spark, sf_dir, name)
    vid = lambda column, kind: (F.col(column).cast("long") * 10 + CODES[kind])
    old = F.lit("1970-01-01 00:00:00").cast("timestamp")
    orders, lines, parts = get("orders"), get("lineitem"), get("part")
    row = lambda df, a, b, label, ts: df.select(a.alias("src"), b.alias("dst"), label.alias("elabel"), ts.alias("ts"))
    state = F.concat("l_returnflag", "l_linestatus")
    day = F.col("l_shipdate").cast("timestamp")
    rows = [
        row(orders, vid("o_custkey", "customer"), vid("o_orderkey", "order"), F.concat(F.lit("CO:"), "o_orderstatus", F.lit(":"), F.substring("o_orderpriority", 1, 1)), F.col("o_orderdate").cast("timestamp")),
        row(lines, vid("l_orderkey", "order"), vid("l_partkey", "part"), F.concat(F.lit("OP:"), state), day),
        row(lines, vid("l_orderkey", "order"), vid("l_suppkey", "supplier"), F.concat(F.lit("OS:"), state), day),
        row(lines.join(parts, F.col("l_partkey") == F.col("p_partkey")), vid("l_partkey", "part"), vid("l_suppkey", "supplier"), F.concat(F.lit("PS:"), "p_type"), day),
        row(get("customer"), vid("c_custkey", "customer"), vid("c_nationkey", "nation"), F.concat(F.lit("CN:"), "c_mktsegment"), old),
        row(get("supplier"), vid("s_suppkey", "supplier"), vid("s_nationkey", "nation"), F.lit("SN"), old),
        row(get("nation"), vid("n_nationkey", "nation"), vid("n_regionkey", "region"), F.lit("NR"), old),
    ]
    every = rows[0]
    for r in rows[1:]:
        every = every.unionByName(r)
    edges = simple(every)
    ends = edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct().withColumn("vlabel", F.lit("any"))
    return PropertyGraph(ends, edges)


def similarity(spark: SparkSession, sf_dir: str, k: int = 8, block: int = 512) -> PropertyGraph:
    """Each vector with its k nearest by cosine; vectors meet in pairs of blocks of fixed size."""
    import numpy as np
    import pandas as pd

    rows = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"), F.col("label").cast("string").alias("label"))
    blocks = max(1, -(-rows.count() // block))
    own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    spread = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    keyed = spread.select("id", "v", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))

    def near(key, part):
        x = np.array(part["v"].tolist())
        x = x / np.linalg.norm(x, axis=1)[:, None]
        ids, mine = part["id"].to_numpy(), part["own"].to_numpy()
        s = x @ x.T
        same = ids[:, None] == ids[None, :]
        s[same | ((mine[:, None] == mine[None, :]) & (key[0] != key[1]))] = -9
        best = np.argsort(-s, axis=1, kind="stable")[:, : k + 1]
        a = np.repeat(np.arange(len(ids)), best.shape[1])
        return pd.DataFrame({"a": ids[a], "b": ids[best.ravel()], "cos": s[a, best.ravel()]}).query("cos > -9")

    pairs = keyed.groupBy("i", "j").applyInPandas(near, "a long, b long, cos double")
    top = pairs.withColumn("n", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("cos"), "b"))).filter(F.col("n") <= k)
    ends = top.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()
    edges = ends.select("src", "dst", F.lit("near").alias("elabel"), F.timestamp_seconds(F.col("dst") * 1000000 + F.col("src")).alias("ts"))
    return PropertyGraph(rows.select(F.col("id").alias("vid"), F.col("label").alias("vlabel")), edges)


GRAPHS = {"copurchase": copurchase, "cobrand": cobrand, "interaction": interaction, "interaction_skew": interaction_skew, "commerce": commerce, "similarity": similarity}
