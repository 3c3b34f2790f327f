"""Work counters per depth, timed runs, and the measures that compare methods."""

from __future__ import annotations

import threading
import time
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdelta.operators.adaptive import enumerate_adaptive
from graphdelta.operators.extend import col, expand, injective
from graphdelta.pattern.model import Pattern
from graphdelta.plans.relations import Change, flagged, term
from graphdelta.sources.storage import cut


def depth_counters(change: Change, q: Pattern, order_of, semantics: str = "iso", rels=None) -> DataFrame:
    """(depth, partials, dead_empty, dead_revisit) over all terms of a batch.

    partials are rows with so many vertices mapped; a row without any candidate is a dead end by emptiness, a
    candidate that is already taken one by revisit.
    """
    parts = []
    one = lambda df, name, depth: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(depth).alias("depth"), F.lit(name).alias("what"), "n")
    marked = flagged(change, q) if rels is None else rels
    for k, (x, y, _) in enumerate(q.edges):
        rels = term(marked, k)
        order = order_of(k, x, y)
        rel = rels[k]
        src, dst = ("src", "dst") if q.edges[k][0] == order[0] else ("dst", "src")
        rows = rel.select(F.col(src).alias(col(order[0])), F.col(dst).alias(col(order[1])))
        parts.append(one(rows, "partials", 2))
        for i in range(2, q.n):
            bound = order[:i]
            wide = cut(expand(rows, rels, q, order[i], bound))
            kept = injective(wide, order[i], bound, semantics)
            parts.append(one(rows.join(wide.select(*[col(u) for u in bound]).distinct(), [col(u) for u in bound], "left_anti"), "dead_empty", i))
            parts.append(one(wide.join(kept, wide.columns, "left_anti"), "dead_revisit", i))
            parts.append(one(kept, "partials", i + 1))
            rows = kept
    long = reduce(DataFrame.unionByName, parts)
    pick = lambda name: F.coalesce(F.sum(F.when(F.col("what") == name, F.col("n"))), F.lit(0)).alias(name)
    return long.groupBy("depth").agg(pick("partials"), pick("dead_empty"), pick("dead_revisit"))


def adaptive_partials(rels: dict[int, DataFrame], q: Pattern, semantics: str = "iso", mode: str = "bound") -> DataFrame:
    """(depth, partials) of the per-row order; rels have (src, dst, new)."""
    seen: list = []
    enumerate_adaptive(rels, q, semantics, mode, seen)
    parts = [t.agg(F.count(F.lit(1)).alias("n")).select(F.lit(depth).alias("depth"), "n") for depth, tables in seen for t in tables]
    return reduce(DataFrame.unionByName, parts).groupBy("depth").agg(F.sum("n").alias("partials"))


def speedup(times: DataFrame, a: str, b: str) -> DataFrame:
    """Mean over queries of the time of b over the time of a; times has (qid, method, t)."""
    pick = lambda m, name: times.filter(F.col("method") == m).select("qid", F.col("t").alias(name))
    return pick(a, "ta").join(pick(b, "tb"), "qid").agg(F.avg(F.col("tb") / F.col("ta")).alias("speedup"))


def relative(values: DataFrame) -> DataFrame:
    """Mean over queries of a method's value over the largest of all methods; values has (qid, method, x)."""
    top = F.max("x").over(Window.partitionBy("qid"))
    return values.withColumn("r", F.when(top == 0, F.lit(1.0)).otherwise(F.col("x") / top)).groupBy("method").agg(F.avg("r").alias("relative"))


def summary(values: DataFrame) -> DataFrame:
    return values.groupBy("method").agg(F.count(F.lit(1)).alias("n"), F.avg("x").alias("mean"), F.stddev_samp("x").alias("deviation"), F.min("x").alias("least"), F.max("x").alias("most"))


def invalid(counters: DataFrame, results: int) -> DataFrame:
    """(n_invalid, n_results): all dead ends of the depths of ``depth_counters``, and final rows."""
    return counters.agg(F.coalesce(F.sum(F.col("dead_empty") + F.col("dead_revisit")), F.lit(0)).alias("n_invalid")).withColumn("n_results", F.lit(results).cast("long"))


def bytes_of(df: DataFrame) -> int:
    """Bytes of the files that a written table (an index ledger's base, arcs) reads."""
    sc = df.sparkSession.sparkContext
    conf = sc._jsc.hadoopConfiguration()
    paths = [sc._jvm.org.apache.hadoop.fs.Path(f) for f in df.inputFiles()]
    return sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in paths)


def status_of(seconds: float, results: int, limit: float, hard_below: int) -> str:
    """solved, unsolved, or hard: unsolved with few results found until then."""
    return "solved" if seconds <= limit else "hard" if results < hard_below else "unsolved"


def timed(df: DataFrame, limit: float = 60.0, hard_below: int = 1_000_000) -> dict:
    """Count a result within a time limit; past it the job is cancelled by its tag, and what its ended tasks found counts."""
    sc = df.sparkSession.sparkContext
    tag = f"timed-{threading.get_ident()}-{time.monotonic_ns()}"
    so_far = sc.accumulator(0)
    out: dict = {}

    def count(batches):
        n = sum(b.num_rows for b in batches)
        so_far.add(n)
        yield pa.RecordBatch.from_arrays([pa.array([n], type=pa.int64())], names=["n"])

    def work() -> None:
        sc.addJobTag(tag)
        sc.setInterruptOnCancel(True)
        try:
            rows = df.select(F.lit(True).alias("one")).mapInArrow(count, "n long")
            out["results"] = rows.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        except Exception as e:  # cancelled, or failed on its own
            out["error"] = str(e)[:200]
        finally:
            sc.removeJobTag(tag)

    began = time.monotonic()
    job = threading.Thread(target=work)
    job.start()
    job.join(limit)
    cancelled = job.is_alive()
    if cancelled:
        sc.cancelJobsWithTag(tag)
        job.join()
    seconds = time.monotonic() - began
    if "error" in out and not cancelled:
        raise RuntimeError(out["error"])
    results = out.get("results", so_far.value)
    return {"seconds": seconds, "results": results, "status": "solved" if "results" in out else status_of(max(seconds, limit + 1e-9), results, limit, hard_below)}
