"""Local recomputation writes what walks along the pattern reach; advice follows the graph's own degree."""

from brute import matches
from test_methods import PATTERNS, edge_df, graph, rows

from graphdelta.methods import matchers as M
from graphdelta.queries import ORACLES, QUERIES
from graphdelta.sources.updates import insertion


def test_local_recompute_leaves_out_what_no_walk_reaches(spark, monkeypatch):
    q = PATTERNS["path"]  # A-B-A-B over label x
    vlabels = {v: "AB"[v % 2] for v in range(6)} | {v: "C" for v in range(6, 40)}
    old = [(v, v + 1, "x") for v in (0, 1, 3, 4)] + [(a, b, "x") for a in range(6) for b in range(6, 40)]
    new, sizes = [(2, 3, "x"), (0, 5, "y")], []
    write = M.cut
    monkeypatch.setattr(M, "cut", lambda df, *name: (t := write(df, *name), sizes.append(t.count()))[0])
    found = M.local_recompute(insertion(graph(spark, vlabels, old), edge_df(spark, new)), q, serialise=True)
    assert rows(found, q, 1) == matches(q, vlabels, old + new) - matches(q, vlabels, old) != set()
    assert max(sizes) < 30  # the arcs to C alone are 408


def test_advice_follows_the_degree(spark, tmp_path):
    spark.createDataFrame([(1, 1, 1), (1, 2, 2), (2, 1, 3), (2, 2, 4)], "l_orderkey long, l_linenumber int, l_partkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    spark.sql("select id o_orderkey, timestamp'2024-01-01' o_orderdate from range(1, 3)").write.parquet(str(tmp_path / "orders.parquet"))
    spark.sql("select id p_partkey, 'PROMO' p_type from range(1, 5)").write.parquet(str(tmp_path / "part.parquet"))
    thin = {r["pid"]: r for r in QUERIES["advise_table"](spark, str(tmp_path)).collect()}
    assert {r["avg_degree"] for r in thin.values()} == {1.0} and thin["sparse6"]["order_choice"] == "direct"
    dense = {r["pid"]: r for r in QUERIES["advise_table"](spark, "/root/testdata/sf0.001").collect()}
    assert dense["sparse6"]["avg_degree"] > 4 and dense["sparse6"]["order_choice"] == "dag"


def test_local_recompute_of_the_path_takes_the_whole_batch(spark):
    d = "/root/testdata/sf0.001"
    local, direct = ([tuple(r) for r in QUERIES[f"delta_{m}_path4"](spark, d).collect()] for m in ("local_recompute", "direct_delta"))
    assert sorted(local) == sorted(direct) != []
    assert ORACLES["delta_local_recompute_path4"] == ORACLES["delta_direct_delta_path4"]
