"""Orders and measures on hand cases, sampled patterns, reports."""

import time

import pytest
from test_methods import edge_df, graph

from graphdelta.functions.sql import geo_mean_speedup, match_count, register, relative_max
from graphdelta.metrics import measures
from graphdelta.operators.extend import match
from graphdelta.pattern.model import parse
from graphdelta.pattern.sample import sample_patterns
from graphdelta.pattern.shape import rooted_dag, rooted_tree, spanning_tree
from graphdelta.plans import orders
from graphdelta.plans.relations import relations
from graphdelta.workloads import grid, unsolved

#: 0-1-2-3 path, 3-4-5 diamond end with 2-4 and 3-5
CASE = parse("01 12 23 34 45 24 35", [None] * 6)


def test_orders_by_hand():
    assert orders.any_connected(CASE) == [0, 1, 2, 3, 4, 5]
    # after 3-4 both 2 and 5 touch two ordered vertices; 2 has the larger degree
    assert orders.order_direct(CASE, (3, 4)) == [3, 4, 2, 5, 1, 0]
    assert orders.order_direct(CASE, (0, 1)) == [0, 1, 2, 3, 4, 5]
    assert orders.order_edges(CASE, [5, 9, 1, 4, 3, 2, 8]) == [2, 5, 4, 3, 6, 1, 0]
    tree = spanning_tree(CASE, [5, 9, 1, 4, 3, 2, 8], [1, 1, 7, 3, 1, 1])
    assert tree.root == 3 and set(tree.edges()) == {(3, 2), (2, 4), (4, 5), (2, 1), (1, 0)}
    assert list(tree.order) == [3, 2, 1, 0, 4, 5]
    paths = {0: 9, 1: 4, 2: 3, 3: 1, 4: 2, 5: 6}
    assert orders.order_paths(tree, paths) == [3, 2, 1, 0, 4, 5]
    assert orders.order_paths(tree, paths, "max") == [3, 2, 4, 1, 5, 0]
    assert orders.order_tree_seeded(CASE, tree, [3, 2, 1, 0, 4, 5], (1, 0)) == [1, 0, 2, 3, 4, 5]
    dag = rooted_dag(CASE)
    assert dag.root == 0 and dag.height() == 5 and list(dag.order) == [0, 1, 2, 3, 4, 5]
    fork = parse("01 02 13", [None] * 4)
    assert list(rooted_tree(fork).order) == [0, 1, 3, 2] and list(rooted_tree(fork, 3).order) == [3, 1, 0, 2]
    assert orders.order_static(CASE, [1] * 7)[0] in (2, 3, 4)  # begins in the dense part
    with pytest.raises(ValueError):
        orders.check_connected(CASE, [0, 2, 1, 3, 4, 5])


def test_measures_by_hand(spark):
    times = spark.createDataFrame([(1, "a", 2.0), (1, "b", 4.0), (2, "a", 1.0), (2, "b", 4.0)], "qid int, method string, t double")
    assert measures.speedup(times, "a", "b").first()[0] == 3.0
    got = {r["method"]: r["relative"] for r in measures.relative(times.withColumnRenamed("t", "x")).collect()}
    assert got == {"a": 0.375, "b": 1.0}
    two = spark.createDataFrame([(1.0, 2.0, 1), (1.0, 8.0, 1), (1.0, 4.0, -1)], "a double, b double, sign int")
    r = two.agg(geo_mean_speedup("a", "b").alias("g"), relative_max("b").alias("r"), match_count().alias("n")).first()
    assert round(r["g"], 9) == 4.0 and round(r["r"], 9) == round(14 / 24, 9) and r["n"] == 1
    deep = spark.createDataFrame([(2, 5, 1, 0), (3, 4, 2, 3)], "depth int, partials long, dead_empty long, dead_revisit long")
    assert tuple(measures.invalid(deep, 7).first()) == (6, 7)
    assert [measures.status_of(s, n, 10, 100) for s, n in ((9, 0), (11, 5), (11, 500))] == ["solved", "hard", "unsolved"]


def test_a_cut_off_count_keeps_what_it_found(spark):
    slow = spark.range(0, 4, 1, 4).mapInPandas(lambda it: (time.sleep(0.0 if p["id"].min() == 0 else 25) or p for p in it), "id long")
    got = measures.timed(slow, 9.0, hard_below=1)
    assert got["status"] == "unsolved" and 1 <= got["results"] < 4
    assert measures.timed(spark.range(10))["results"] == 10


def test_sampled_patterns_have_matches_and_reports(spark):
    vlabels = {v: "AB"[v % 2] for v in range(14)}
    edges = [(a, b, "x") for a in range(14) for b in range(a + 1, 14) if (a * 7 + b * 3) % 3 == 0 or b - a == 1]
    g = graph(spark, vlabels, edges)
    arcs = g.arcs()
    for kind, size in (("tree", 4), ("sparse", 4), ("dense", 5)):
        for q in (found := sample_patterns(arcs, size, kind, 2)):
            assert (q.n, q.density_class) == (size, kind)
            assert match(relations(arcs, q), q, orders.any_connected(q)).limit(1).count()
        assert found
    q = sample_patterns(arcs, 4, "tree", 1)[0]
    batch = edge_df(spark, edges[-2:]).selectExpr("'+' op", "*")
    report = grid(spark, "small", graph(spark, vlabels, edges[:-2]), batch, [q], ["direct_delta", "tree_index"]).collect()
    assert len({r["results"] for r in report}) == 1 and {r["status"] for r in report} == {"solved"}
    late = spark.createDataFrame([("tree", "a", "hard"), ("tree", "a", "solved"), ("tree", "a", "unsolved")], "kind string, method string, status string")
    assert tuple(unsolved(late).first()) == ("tree", "a", 3, 2, 1)


def test_functions_in_sql(spark):
    register(spark)
    text = CASE.to_json()
    assert spark.sql(f"select pattern_class('{text}') c, pattern_diameter('{text}') d").first() == ("sparse", 4)
    assert spark.sql(f"select count(*) from pattern_edges('{text}')").first()[0] == 7
