"""Batches of a stream in one plan: against brute force batch by batch, and as many Spark jobs for many batches as for few."""

from concurrent.futures import ThreadPoolExecutor

import pytest
from brute import matches
from test_methods import PATTERNS, TS, graph, random_case

from graphdelta import surface
from graphdelta.methods.state import TOGETHER, apply_batch, apply_batches, prepare

OPS = "batch_id long, seq long, op string, src long, dst long, elabel string, t string"


def stream_of(spark, batches):
    rows = [(i, n, op, a, b, label, TS) for i, ops in enumerate(batches) for n, (op, a, b, label) in enumerate(ops)]
    return spark.createDataFrame(rows, OPS).selectExpr("batch_id", "seq", "op", "src", "dst", "elabel", "cast(t as timestamp) ts").coalesce(1)


def dealt(seed, q, deletions):
    """A graph, batches that deal out half of its edges in turn, repeated and with a second label, and the graph after each."""
    vlabels, old, new = random_case(seed)
    every = old + new
    now, rest = every[::2], every[1::2]
    batches = [[("+", *e) for e in rest[i::4]] for i in range(4)]
    batches[1] += [("+", b, a, "y" if label == "x" else "x") for a, b, label in rest[0::4]] + [("+", 5, 5, "x"), ("+", *now[0])]
    if deletions:
        batches.insert(2, [("-", *now[1]), ("-", *rest[0]), ("+", *rest[0])])
    graphs = [now]
    for i, ops in enumerate(batches):
        gone = [now[1]] if deletions and i == 2 else []
        have = {e[:2] for e in graphs[-1]}
        graphs.append([e for e in graphs[-1] if e not in gone] + [e[1:] for e in ops if e[0] == "+" and e[1] < e[2] and e[1:3] not in have])
    return vlabels, now, batches, graphs


def net_of(found, q):
    net = found.groupBy("batch_id", *[f"m{u}" for u in range(q.n)]).sum("sign").filter("`sum(sign)` != 0").collect()
    return {(r[0], tuple(r)[1:-1], r[-1]) for r in net}


def test_every_method_gives_each_batch_its_matches(spark):
    q = PATTERNS["path"]
    vlabels, old, batches, graphs = dealt(21, q, False)
    want = [matches(q, vlabels, e) for e in graphs]
    g, stream = graph(spark, vlabels, old), stream_of(spark, batches)
    with ThreadPoolExecutor(8) as pool:
        got = pool.map(lambda m: net_of(apply_batches(prepare(g, q, m), stream)[1], q), TOGETHER)
        for method, net in zip(TOGETHER, got, strict=True):
            assert net == {(i, m, 1) for i, (a, b) in enumerate(zip(want, want[1:])) for m in b - a} != set(), method


@pytest.mark.parametrize("name,semantics,deletions", [("path", "hom", False), ("square", "iso", True), ("path", "iso", True)])
@pytest.mark.parametrize("method", ["direct_delta", "cached_join_tree"])
def test_batches_of_a_stream(spark, method, name, semantics, deletions):
    q = PATTERNS[name]
    vlabels, old, batches, graphs = dealt(21, q, deletions and method != "cached_join_tree")
    want = [matches(q, vlabels, e, semantics) for e in graphs]
    state, found = apply_batches(prepare(graph(spark, vlabels, old), q, method, semantics), stream_of(spark, batches))
    assert net_of(found, q) == {(i, m, s) for i, (a, b) in enumerate(zip(want, want[1:])) for s, more in ((1, b - a), (-1, a - b)) for m in more}
    # the state goes on where the stream ended
    edge = next(e for e in old if e in graphs[-1])
    op = ("-", *edge) if method != "cached_join_tree" else ("+", *edge)
    _, last = apply_batch(state, stream_of(spark, [[op]]).drop("batch_id"))
    after = matches(q, vlabels, [e for e in graphs[-1] if e != edge or op[0] == "+"], semantics)
    assert {tuple(r)[:-1] for r in last.collect()} == want[-1] - after


@pytest.mark.parametrize("method", ["direct_delta", "cached_join_tree"])
def test_jobs_do_not_grow_with_the_batches(spark, monkeypatch, method):
    q = surface.PATH
    jobs, counts = [], []
    for size in (150, 20):
        monkeypatch.setattr(surface, "SIZE", size)
        spark.sparkContext.setJobGroup(f"{method}-{size}", "")
        counts.append({r["batch_id"]: r["n"] for r in surface._in_turn(method, q)(spark, "/root/testdata/sf0.001").collect()})
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"{method}-{size}")))
    spark.sparkContext.setJobGroup("rest", "")
    assert len(counts[1]) > len(counts[0]) and sum(counts[0].values()) == sum(counts[1].values()) > 0
    assert jobs[1] <= jobs[0] + 5
