"""Experiment runs: methods over sets of patterns and a stream, with the reports that compare them."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdelta.metrics import measures
from graphdelta.methods.state import apply_change, changes_of, prepare
from graphdelta.pattern.model import Pattern, UnsupportedPattern, UnsupportedUpdate
from graphdelta.sources.graph import PropertyGraph

REPORT = "graph string, pid string, kind string, method string, semantics string, build_time double, t_index double, t_enum double, response_time double, results long, status string"


def one_run(g: PropertyGraph, q: Pattern, method: str, batch: DataFrame, semantics: str = "iso", time_limit: float = 60.0, hard_below: int = 1_000_000, enumerate_matches: bool = True) -> dict:
    """One query over one batch: offline build, index upkeep and enumeration apart; past the limit it is cancelled.

    ``status`` is solved, unsolved, or hard when it was cut off with few matches, unsupported where the method does not take it.
    """
    import time

    out = {"pid": q.name, "kind": q.density_class, "method": method, "semantics": semantics, "build_time": 0.0, "t_index": 0.0, "t_enum": 0.0, "results": 0, "status": "solved"}
    try:
        began = time.monotonic()
        state = prepare(g, q, method, semantics)
        out["build_time"] = time.monotonic() - began
        for change in changes_of(state, batch):
            if not change.count():
                continue
            began = time.monotonic()
            state, found = apply_change(state, change, enumerate_matches=enumerate_matches)
            out["t_index"] += time.monotonic() - began
            if found is not None:
                timed = measures.timed(found, max(0.1, time_limit - out["t_index"] - out["t_enum"]), hard_below)
                out["t_enum"] += timed["seconds"]
                out["results"] += timed["results"]
                out["status"] = timed["status"]
            if out["status"] != "solved":
                break
    except (UnsupportedPattern, UnsupportedUpdate):
        out["status"] = "unsupported"
    return out | {"response_time": out["t_index"] + out["t_enum"]}


def grid(spark: SparkSession, name: str, g: PropertyGraph, batch: DataFrame, patterns: Iterable[Pattern], methods: Iterable[str], **settings) -> DataFrame:
    """One row a pattern and method, as ``REPORT``."""
    names = [c.split()[0] for c in REPORT.split(", ")]
    rows = [one_run(g, q, m, batch, **settings) | {"graph": name} for q in patterns for m in methods]
    return spark.createDataFrame([tuple(r[c] for c in names) for r in rows], REPORT)


def unsolved(report: DataFrame) -> DataFrame:
    """(kind, method, n, n_unsolved, n_hard): unsolved counts the hard ones too."""
    return report.filter("status != 'unsupported'").groupBy("kind", "method").agg(
        F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("status") != "solved", 1)).alias("n_unsolved"), F.count(F.when(F.col("status") == "hard", 1)).alias("n_hard")
    )


def details(report: DataFrame) -> DataFrame:
    """The report of one set of patterns, each method's queries by response time."""
    return report.orderBy("method", "response_time", "pid")
