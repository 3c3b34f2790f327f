"""Batches applied one after the other, streams and restarts, normalising, numbering: against brute force."""

import random
from concurrent.futures import ThreadPoolExecutor

import pytest
from brute import matches
from test_methods import PATTERNS, TS, edge_df, graph, random_case, rows

from graphdelta.methods import matchers as M
from graphdelta.methods.state import apply_batch, maintained, prepare, run
from graphdelta.sources.graph import numbered, split_stream
from graphdelta.sources.updates import normalise, slide
from graphdelta.streaming.runner import StreamMatcher, Watermark, activity, file_updates


def batch_of(spark, ops):
    rows = [(i, op, a, b, label, TS) for i, (op, a, b, label) in enumerate(ops)]
    return spark.createDataFrame(rows, "seq long, op string, src long, dst long, elabel string, t string").selectExpr("seq", "op", "src", "dst", "elabel", "cast(t as timestamp) ts").coalesce(1)


@pytest.fixture(autouse=True)
def one_partition(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "1")
    yield
    spark.conf.set("spark.sql.shuffle.partitions", before)


def turns(seed):
    """A graph and three batches: insertions, deletions, both with a relabelled edge and no-ops."""
    vlabels, old, new = random_case(seed)
    gone = old[:3]
    a, b, label = old[4]
    mixed = [("-", *new[0]), ("+", *gone[0]), ("-", a, b, label), ("+", b, a, "y" if label == "x" else "x"), ("+", 5, 5, "x"), ("+", *old[5]), ("-", 0, 8, "zz")]
    after = [old + new, [e for e in old if e not in gone] + new]
    last = [e for e in after[1] if e != new[0] and e != old[4]] + [gone[0], (a, b, "y" if label == "x" else "x")]
    return vlabels, old, [[("+", *e) for e in new], [("-", *e) for e in gone], mixed], [old, *after, last]


@pytest.mark.parametrize("name,semantics", [("path", "hom"), ("square", "iso")])
def test_batches_in_turn(spark, name, semantics):
    q = PATTERNS[name]
    vlabels, old, ops, graphs = turns(11)
    want = [matches(q, vlabels, e, semantics) for e in graphs]
    g = graph(spark, vlabels, old)

    def go(method):
        state, got = prepare(g, q, method, semantics), []
        for op in ops[: 1 if method == "cached_join_tree" else 3]:
            state, found = apply_batch(state, batch_of(spark, op))
            found = found.groupBy(*[f"m{u}" for u in range(q.n)]).sum("sign").withColumnRenamed("sum(sign)", "sign").filter("sign != 0")
            got.append((rows(found, q, 1), rows(found, q, -1)))
        return got

    methods = ["direct_delta", "cached_join_tree", "tree_index", "dag_index", "tree_dag", "direct_dag", *(["bottomup_index", "bottomup_dag"] if q.is_tree else [])]
    with ThreadPoolExecutor(8) as pool:
        for method, got in zip(methods, pool.map(go, methods), strict=True):
            assert got == [(b - a, a - b) for a, b in zip(want, want[1:], strict=False)][: len(got)], method


def test_run_reports_and_maintained_result(spark):
    q = PATTERNS["path"]
    vlabels, old, ops, graphs = turns(12)
    g = graph(spark, vlabels, old)
    stored = spark.createDataFrame([*matches(q, vlabels, old)] or [], "m0 long, m1 long, m2 long, m3 long")
    state = prepare(g, q)
    state, found = apply_batch(state, batch_of(spark, ops[0]))
    after = maintained(stored, found)
    assert rows(after, q) == matches(q, vlabels, graphs[1])
    state, reports = run(state, [batch_of(spark, ops[1]), batch_of(spark, [])])
    assert [r["results"] for r in reports] == [len(matches(q, vlabels, graphs[1]) - matches(q, vlabels, graphs[2])), 0]
    assert all(r["status"] == "solved" for r in reports)


def test_stream_goes_on_after_a_restart(spark, tmp_path):
    q = PATTERNS["path"]
    vlabels, old, ops, graphs = turns(13)
    g = graph(spark, vlabels, old)
    folder = str(tmp_path / "updates")
    for op in ops[:2]:
        batch_of(spark, op).select("seq", "op", "src", "dst", "elabel", "ts").write.mode("append").parquet(folder)
        StreamMatcher(g, q, str(tmp_path / "run"), "tree_index").run(file_updates(spark, folder))  # a new matcher each time
    got = StreamMatcher(g, q, str(tmp_path / "run")).matches(spark)
    assert rows(got, q, 1) == matches(q, vlabels, graphs[1]) - matches(q, vlabels, graphs[0])
    assert rows(got, q, -1) == matches(q, vlabels, graphs[1]) - matches(q, vlabels, graphs[2])


def timed_rows(spark, rows):
    return spark.createDataFrame(rows, "k long, t string").selectExpr("k", "cast(t as timestamp) ts").coalesce(1)


def test_late_rows_are_counted_and_split_off(spark, tmp_path):
    batches = [[(1, "2024-01-05"), (2, "2024-01-01"), (3, None)], [(4, "2024-01-03 23:59:59"), (5, "2024-01-04"), (6, "2024-01-09"), (7, None)], [(8, "2024-01-07"), (9, "2024-01-08")], []]
    for again in range(2):  # a restart replays all batches
        mark = Watermark(str(tmp_path), 86_400)
        got = [{r["k"] for r in mark.in_time(timed_rows(spark, b), i).collect()} for i, b in enumerate(batches)]
        assert got == [{1, 2, 3}, {5, 6, 7}, {9}, set()]
        assert [r["n_late"] for r in mark.marks(spark).orderBy("batch_id").collect()] == [0, 1, 1, 0]


def test_state_by_key_is_carried_between_triggers(spark, tmp_path):
    folder, out = str(tmp_path / "in"), {}
    for b in [[(1, "2024-01-05"), (2, "2024-01-01"), (None, "2024-01-01")], [(1, "2024-01-03"), (1, "2024-01-04"), (2, None)]]:
        timed_rows(spark, b).write.mode("append").parquet(folder)
        stream = activity(spark.readStream.schema("k long, ts timestamp").parquet(folder), "k")
        take = lambda df, i: out.__setitem__(i, {(r["key"], r["n"], str(r["first"])[:10], str(r["last"])[:10]) for r in df.collect()})
        stream.writeStream.outputMode("update").foreachBatch(take).option("checkpointLocation", str(tmp_path / "check")).trigger(availableNow=True).start().awaitTermination()
    assert out[0] == {(1, 1, "2024-01-05", "2024-01-05"), (2, 1, "2024-01-01", "2024-01-01")}
    assert out[1] == {(1, 3, "2024-01-03", "2024-01-05")}


@pytest.mark.parametrize("ops,minus,plus", [("-+-", 1, 0), ("+-", 1, 0), ("-+", 0, 0), ("+", 0, 0), ("-", 1, 0)])
def test_the_last_operation_on_a_present_edge_counts(spark, ops, minus, plus):
    edges = edge_df(spark, [(1, 2, "x")])
    gone, came = normalise(batch_of(spark, [(op, 2, 1, "x") for op in ops]), edges)
    assert (gone.count(), came.count()) == (minus, plus)
    gone, came = normalise(batch_of(spark, [(op, 3, 4, "x") for op in ops]), edges)
    assert (gone.count(), came.count()) == (0, int(ops[-1] == "+"))


def test_numbering_and_split(spark):
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    rng = random.Random(1)
    pairs = rng.sample([(a, b) for a in range(30) for b in range(a + 1, 30)], 100)
    edges = edge_df(spark, [(a, b, "x") for a, b in pairs])
    got = {(r["src"], r["dst"]): r["n"] for r in numbered(edges, "ts", "src", "dst").collect()}
    assert got == {e: i for i, e in enumerate(sorted(pairs))}
    first, last = split_stream(edges, 0.1)
    assert {(r["src"], r["dst"]) for r in last.collect()} == set(sorted(pairs)[90:]) and first.count() == 90


def test_sliding_window_batch(spark):
    day = lambda d: f"2024-01-{d:02d} 00:00:00"
    edges = spark.createDataFrame([(i, i + 1, "x", day(i)) for i in range(1, 9)], "src long, dst long, elabel string, t string").selectExpr("src", "dst", "elabel", "cast(t as timestamp) ts")
    got = {(r["op"], r["src"]) for r in slide(edges, day(4), day(6), "3 days").collect()}
    assert got == {("-", 2), ("-", 3), ("+", 5), ("+", 6)}


def test_the_plan_of_a_batch(spark):
    """Relations are file scans with their labels pushed down; no product, no loop, no Python."""
    q = PATTERNS["path"]
    vlabels, old, ops, _ = turns(14)
    state = prepare(graph(spark, vlabels, old), q)
    _, found = apply_batch(state, batch_of(spark, ops[0]))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet" in plan and "EqualTo(elabel,x)" in plan and "EqualTo(slabel," in plan
    assert not any(x in plan for x in ("CartesianProduct", "BroadcastNestedLoop", "Python", "ExistingRDD"))
    assert M.SUPPORT.keys() >= {"direct_delta"}
