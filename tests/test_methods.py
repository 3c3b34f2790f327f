"""Every method against brute force on small random graphs and on the worked example."""

import random
from concurrent.futures import ThreadPoolExecutor

import pytest
from brute import candidates, matches

from graphdelta.methods import matchers as M
from graphdelta.operators.extend import match
from graphdelta.pattern.model import UnsupportedPattern, UnsupportedUpdate, parse
from graphdelta.pattern.shape import rooted_dag
from graphdelta.plans.orders import any_connected, order_static
from graphdelta.plans.relations import relations
from graphdelta.sources.graph import PropertyGraph
from graphdelta.sources.updates import deletion, insertion

TS = "2024-01-01 00:00:00"


def graph(spark, vlabels, edges):
    v = spark.createDataFrame(sorted(vlabels.items()), "vid long, vlabel string")
    return PropertyGraph(v, edge_df(spark, edges))


def edge_df(spark, edges):
    return spark.createDataFrame([(min(s, d), max(s, d), label, TS) for s, d, label in edges], "src long, dst long, elabel string, t string").selectExpr("src", "dst", "elabel", "cast(t as timestamp) ts").coalesce(1)


def rows(df, q, sign=None):
    got = [tuple(r[f"m{u}"] for u in range(q.n)) for r in df.collect() if sign is None or r["sign"] == sign]
    assert len(got) == len(set(got)), "a match came twice"
    return set(got)


def random_case(seed, n=9, m=14):
    rng = random.Random(seed)
    vlabels = {v: rng.choice("AB") for v in range(n)}
    pairs = rng.sample([(a, b) for a in range(n) for b in range(a + 1, n)], m)
    edges = [(a, b, rng.choice("xxy")) for a, b in pairs]
    return vlabels, edges[:-4], edges[-4:]


PATTERNS = {
    "path": parse("01 12 23", "ABAB", "x"),
    "triangle": parse("01 12 02", [None, None, "A"], ["x", "x", None]),
    "square": parse("01 12 23 03", ["A", None, "A", None], None),
    "fork": parse("01 02 13", [None, "B", None, "A"], None),
}


@pytest.fixture(autouse=True)
def one_partition(spark):
    """The tables are tiny: one task a stage."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "1")
    yield
    spark.conf.set("spark.sql.shuffle.partitions", before)


def together(run, names):
    """Results of several methods, run at the same time: small jobs mostly wait."""
    with ThreadPoolExecutor(6) as pool:
        return dict(zip(names, pool.map(run, names), strict=True))


@pytest.mark.parametrize("name,seed,semantics", [("path", 1, "iso"), ("triangle", 1, "iso"), ("square", 2, "hom"), ("fork", 2, "hom")])
def test_all_methods_agree(spark, name, seed, semantics):
    q = PATTERNS[name]
    vlabels, old, new = random_case(seed)
    g = graph(spark, vlabels, old)
    want = matches(q, vlabels, old + new, semantics) - matches(q, vlabels, old, semantics)
    change = insertion(g, edge_df(spark, new))
    fit = [m for m in M.METHODS if q.is_tree or not m.startswith("bottomup")]
    got = together(lambda m: rows(M.run_method(m, change, q, g.vertices, semantics), q, 1), fit)
    assert got == {m: want for m in fit}
    for method in set(M.METHODS) - set(fit):
        with pytest.raises(UnsupportedPattern):
            M.run_method(method, change, q, g.vertices, semantics)


@pytest.mark.parametrize("name", ["path", "triangle"])
def test_deletions(spark, name):
    q = PATTERNS[name]
    vlabels, old, new = random_case(3)
    g = graph(spark, vlabels, old + new)
    want = matches(q, vlabels, old + new) - matches(q, vlabels, old)
    change = deletion(g, edge_df(spark, new))
    fit = [m for m in M.METHODS if m != "cached_join_tree" and (q.is_tree or not m.startswith("bottomup"))]
    assert together(lambda m: rows(M.run_method(m, change, q, g.vertices), q, -1), fit) == {m: want for m in fit}


def test_support(spark):
    """What a method does not take as published raises."""
    vlabels, old, new = random_case(3)
    q, g = PATTERNS["path"], graph(spark, vlabels, old + new)
    gone, came = deletion(g, edge_df(spark, new)), insertion(graph(spark, vlabels, old), edge_df(spark, new))
    with pytest.raises(UnsupportedUpdate):
        M.run_method("cached_join_tree", gone, q, g.vertices)
    for method, support in M.SUPPORT.items():
        if not support[6]:
            with pytest.raises(UnsupportedUpdate):
                M.run_method(method, came, q, g.vertices, limit=1)
        if not support[5]:
            with pytest.raises(UnsupportedUpdate):
                M.run_method(method, came, q, g.vertices, batch_mode="serial")
    few = M.direct_delta(came, q, limit=2)
    want = matches(q, vlabels, old + new) - matches(q, vlabels, old)
    assert len(rows(few, q)) == min(2, len(want)) and rows(few, q) <= want


@pytest.mark.parametrize("index", ["tree", "dag", "bottomup"])
def test_updated_index_equals_rebuilt(spark, index):
    q = PATTERNS["path" if index == "bottomup" else "square"]
    vlabels, old, new = random_case(5)
    g = graph(spark, vlabels, old)
    gone, kept = old[:3], old[3:]
    insert = insertion(g, edge_df(spark, new))
    ix = M.build_index(index, q, g.arcs(), g.vertices)
    after = ix.updated(insert)
    g2 = graph(spark, vlabels, old + new)
    last = after.updated(deletion(g2, edge_df(spark, gone)))
    for state, edges in ((ix, old), (after, old + new), (last, kept + new)):
        up, down = candidates(q, ix.shape, vlabels, edges, index != "bottomup")
        for u in range(q.n):
            assert {r["vid"] for r in state.up[u].vids().collect()} == up[u]
            assert {r["vid"] for r in state.down[u].vids().collect()} == down[u]


def test_worked_example(spark):
    vlabels = dict(enumerate("AAAABCBCDDD"))
    old = [(0, 4), (0, 5), (4, 8), (5, 8), (2, 6), (2, 5), (5, 10), (3, 6), (3, 7), (1, 4), (7, 9)]
    old = [(a, b, "e") for a, b in old]
    q = parse("01 02 13 23", "ABCD", "e")
    tree = parse("01 02 13", "ABCD", "e")
    g = graph(spark, vlabels, old)
    change = insertion(g, edge_df(spark, [(6, 10, "e")]))
    assert rows(M.direct_delta(change, q), q) == {(2, 6, 5, 10)}
    assert rows(M.dag_index(change, q, g.vertices), q) == {(2, 6, 5, 10)}
    assert rows(M.bottomup_index(change, tree, g.vertices), tree) == {(2, 6, 5, 10), (3, 6, 7, 10)}
    ix = M.build_index("bottomup", tree, change.base, g.vertices)
    local = M.local_sets(ix, change, 2, M.term(M.flagged(change, tree), 2))
    assert {u: {r["vid"] for r in rows.collect()} for u, rows in local.items()} == {0: {2, 3}, 1: {6}}
    g2 = graph(spark, vlabels, [*old, (6, 10, "e")])
    gone = deletion(g2, edge_df(spark, [(0, 4, "e")]))
    assert rows(M.direct_delta(gone, q), q, -1) == {(0, 4, 5, 8)}


def test_static_matching_orders_and_strategies(spark):
    vlabels, old, new = random_case(8, 10, 20)
    g = graph(spark, vlabels, old + new)
    for q in PATTERNS.values():
        for semantics in ("iso", "hom"):
            want = matches(q, vlabels, old + new, semantics)
            rels = relations(g.arcs(), q)
            assert rows(match(rels, q, any_connected(q), semantics), q) == want
            assert rows(match(rels, q, order_static(q, [1] * q.m), semantics, "least"), q) == want


def test_audit_finds_nothing(spark):
    vlabels, old, new = random_case(9)
    g = graph(spark, vlabels, old + new)
    q = PATTERNS["square"]
    ix = M.build_index("dag", q, g.arcs(), g.vertices)
    assert ix.shape.order == rooted_dag(q).order
    found = match(relations(g.arcs(), q), q, any_connected(q), "hom")
    assert ix.audit(found, g.arcs()).count() == 0
