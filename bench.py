"""Headline queries, timed: prints one JSON line.  BENCH_SF_DIR and BENCH_CPUS choose tables and threads."""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession

#: Queries from their tables to their rows, and methods timed over one batch of a hundredth of the edges, offline work apart.
HEADLINE = ["match_path4", "match_tree6", "match_sparse6", "static_snapshot_net_change", "commerce_edges", "delta_direct_commerce_c_tri"]
ONLINE = ["full_recompute", "direct_delta", "cached_join_tree", "tree_index", "dag_index", "bottomup_index"]


def main() -> None:
    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from graphdelta.queries import QUERIES

    from graphdelta.methods.state import apply_change, prepare
    from graphdelta.queries import pattern, s90
    from graphdelta.sources.updates import insertion

    def seconds(df) -> float:
        began = time.monotonic()
        df().write.format("noop").mode("overwrite").save()
        return time.monotonic() - began

    out, repeats = {}, int(os.environ.get("BENCH_REPEATS", "1"))
    seconds(lambda: QUERIES["match_wedge3"](spark, d))  # warm-up
    for name in HEADLINE:
        out[name] = round(statistics.median(seconds(lambda name=name: QUERIES[name](spark, d)) for _ in range(repeats)), 3)
    g, new = s90(spark, d, "copurchase", 0.01)
    change, q = insertion(g, new), pattern("copurchase", "path4")
    for method in ONLINE:
        state = prepare(g, q, method)
        out[f"online_{method}_path4"] = round(statistics.median(seconds(lambda state=state: apply_change(state, change)[1]) for _ in range(repeats)), 3)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": d.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
