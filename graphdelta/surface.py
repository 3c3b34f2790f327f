"""Further registered queries: relational operations on matches, batches in turn, windows, relabelling, pruning, streams."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta import queries as Q
from graphdelta.index.candidates import label_candidates
from graphdelta.methods import matchers as M
from graphdelta.methods.state import apply_batch, apply_batches, maintained, prepare
from graphdelta.operators import relational as R
from graphdelta.operators.extend import match
from graphdelta.pattern.model import Pattern
from graphdelta.plans import orders
from graphdelta.plans.relations import relation, relations
from graphdelta.sources import builders, updates
from graphdelta.sources.graph import PropertyGraph
from graphdelta.sources.storage import cut, shared_dir

register, build, s90 = Q.register, Q.build, Q.s90
PATH, TRI, WEDGE = (Q.pattern("copurchase", x) for x in ("path4", "tri3", "wedge3"))
CO = Q._base("copurchase")
INTER = Q.EDGES_SQL["interaction"]


def matched(spark, d: str, graph: str, q: Pattern, semantics: str = "iso") -> tuple[PropertyGraph, DataFrame, DataFrame]:
    """A graph, its written arcs, and all matches of a pattern."""
    g = build(spark, d, graph)
    arcs = cut(g.arcs(), "arcs")
    return g, arcs, match(relations(arcs, q), q, orders.any_connected(q), semantics)


def net(signed: DataFrame) -> DataFrame:
    """Signed matches with those that come and go again taken out."""
    cols = [c for c in signed.columns if c != "sign"]
    return signed.groupBy(*cols).agg(F.sum("sign").cast("int").alias("sign")).filter("sign != 0")


# ---------------------------------------------------------------- relational operations

C_EDGE = Pattern((None, None), ((0, 1, "OP:NO"),), "c_edge")


@register("optional_edge", f"{Q._base('commerce')} SELECT a.src AS m0, a.dst AS m1, b.dst AS m2 FROM (SELECT src, dst FROM arcs WHERE elabel = 'OP:NO') a LEFT JOIN (SELECT src, dst FROM arcs WHERE elabel = 'PS:ECONOMY') b ON a.dst = b.src")
def optional_edge(s, d):
    _, arcs, found = matched(s, d, "commerce", C_EDGE)
    return R.optional(found, arcs.filter("elabel = 'PS:ECONOMY'"), 1, 2)


@register("interval_wedge", f"WITH e AS MATERIALIZED ({INTER}), a AS (SELECT src, dst, ts FROM e UNION ALL SELECT dst, src, ts FROM e) SELECT x.src AS mid, x.dst AS a, y.dst AS b FROM a x JOIN a y ON x.src = y.src AND x.dst < y.dst AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 3600000000")
def interval_wedge(s, d):
    e = build(s, d, "interaction").edges
    return R.interval_wedge(e.select("src", "dst", "ts").unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "ts")), 3600)


@register("asof_label", f"WITH e AS MATERIALIZED ({INTER}) SELECT e.src, e.dst, arg_max(v.event_type, CAST(epoch_us(v.ts) AS HUGEINT) * 10000000 + v.event_id) AS label FROM e LEFT JOIN events v ON v.user_id = e.src AND v.ts <= e.ts GROUP BY 1, 2")
def asof_label(s, d):
    labels = builders.read(s, d, "events").select(F.col("user_id").alias("vid"), "ts", F.col("event_id").alias("seq"), F.col("event_type").alias("label"))
    return R.label_as_of(build(s, d, "interaction").edges, labels)


@register("json_label_edges", "SELECT CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k, count(*) AS n, count(DISTINCT user_id) AS n_users FROM events GROUP BY 1")
def json_label_edges(s, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return builders.read(s, d, "events").groupBy(k.alias("k")).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("user_id").alias("n_users"))


@register("match_as_map", f"{CO}, {Q._matches(TRI, 'true', 'hit')} " + " UNION ALL ".join(f"SELECT {u} AS u, m{u} AS vid, count(*) AS n FROM hit GROUP BY 2" for u in range(3)))
def match_as_map(s, d):
    found = matched(s, d, "copurchase", TRI)[2]
    return R.as_map(found, 3).select(F.explode("m").alias("u", "vid")).groupBy("u", "vid").agg(F.count(F.lit(1)).alias("n"))


@register("where_matches", f"{Q._base('commerce')}, {Q._matches(Q.COMMERCE['c_path'], 'true', 'hit')} SELECT hit.* FROM hit JOIN orders ON m1 = o_orderkey * 10 + 1 WHERE o_totalprice > 100000")
def where_matches(s, d):
    found = matched(s, d, "commerce", Q.COMMERCE["c_path"])[2]
    prices = builders.read(s, d, "orders").select((F.col("o_orderkey") * 10 + 1).alias("vid"), "o_totalprice")
    return R.with_attributes(found, 1, prices, F.col("o_totalprice") > 100000)


@register("topk_vertices", f"{CO}, {Q._matches(TRI, 'true', 'hit')} SELECT vid, n FROM (SELECT vid, count(*) AS n FROM (SELECT unnest([m0, m1, m2]) AS vid FROM hit) GROUP BY vid) ORDER BY n DESC, vid LIMIT 10")
def topk_vertices(s, d):
    found = matched(s, d, "copurchase", TRI)[2]
    return found.select(F.explode(F.array("m0", "m1", "m2")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "vid").limit(10)


@register("intersect_neighbours", f"WITH e AS MATERIALIZED ({INTER}), a AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) SELECT e.src, e.dst, count(y.dst) AS n FROM e LEFT JOIN a x ON x.src = e.src LEFT JOIN a y ON y.src = e.dst AND y.dst = x.dst GROUP BY 1, 2")
def intersect_neighbours(s, d):
    g = build(s, d, "interaction")
    return R.common_neighbours(g.edges, g.arcs())


@register("except_relations", f"{CO} SELECT a.src, a.dst FROM arcs a JOIN verts v ON a.src = v.vid WHERE v.vlabel = '{PATH.vlabels[0]}' EXCEPT SELECT src, dst FROM arcs WHERE old")
def except_relations(s, d):
    g, new = s90(s, d, "copurchase")
    change = updates.insertion(g, new)
    return change.full.filter(F.col("slabel") == PATH.vlabels[0]).select("src", "dst").exceptAll(change.rest.filter(F.col("slabel") == PATH.vlabels[0]).select("src", "dst"))


_LABELLED = f"{CO} SELECT vlabel, CAST(rn > floor(0.9 * total) AS INTEGER) AS late, count(*) AS n FROM ranked JOIN verts ON src = vid"


def _labelled_stream(s, d):
    g, new = s90(s, d, "copurchase")
    return g.edges.withColumn("late", F.lit(0)).unionByName(new.withColumn("late", F.lit(1))).join(g.vertices, F.col("src") == F.col("vid"))


register("rollup_stream", f"{_LABELLED} GROUP BY ROLLUP (vlabel, CAST(rn > floor(0.9 * total) AS INTEGER))")(lambda s, d: _labelled_stream(s, d).rollup("vlabel", "late").agg(F.count(F.lit(1)).alias("n")))


@register("grouping_sets_stream", f"{_LABELLED} GROUP BY GROUPING SETS ((vlabel), (CAST(rn > floor(0.9 * total) AS INTEGER)), ())")
def grouping_sets_stream(s, d):
    rows = _labelled_stream(s, d)
    return s.sql("SELECT vlabel, late, count(*) AS n FROM {rows} GROUP BY GROUPING SETS ((vlabel), (late), ())", rows=rows)


# ---------------------------------------------------------------- batches in turn

SIZE = 1000
_RANKED = "(SELECT src, dst, elabel, greatest(rn - CAST(floor(0.9 * total) AS BIGINT) - 1, -1) AS seq FROM ranked UNION ALL SELECT dst, src, elabel, greatest(rn - CAST(floor(0.9 * total) AS BIGINT) - 1, -1) FROM ranked)"


def _by_batch_sql(q: Pattern) -> str:
    """A match arrives with the last of its edges."""
    hit = Q._matches(q, "true", "hit")
    joins = " ".join(f"JOIN r r{e} ON r{e}.src = m{u} AND r{e}.dst = m{w}" for e, (u, w, _) in enumerate(q.edges))
    last = f"greatest({', '.join(f'r{e}.seq' for e in range(q.m))})"
    return f"{CO}, r AS MATERIALIZED {_RANKED}, {hit} SELECT CAST(floor({last} / {SIZE}.0) AS BIGINT) AS batch_id, count(*) AS n FROM hit {joins} WHERE {last} >= 0 GROUP BY 1"


def _in_turn(method: str, q: Pattern):
    def run(s, d):
        g, new = s90(s, d, "copurchase")
        _, found = apply_batches(prepare(g, q, method), updates.batches(new, SIZE))
        return found.groupBy("batch_id").agg(F.count(F.lit(1)).alias("n"))

    return run


for _method, _q in (("direct_delta", PATH), ("cached_join_tree", PATH), ("tree_index", PATH), ("dag_index", TRI), ("bottomup_index", PATH), ("direct_dag", TRI)):
    register(f"batches_in_turn_{_method}", _by_batch_sql(_q))(_in_turn(_method, _q))


def _windowed(where: str) -> str:
    return f"arcs_{where} AS MATERIALIZED (SELECT src, dst, elabel FROM e WHERE {where} UNION ALL SELECT dst, src, elabel FROM e WHERE {where})"


INTER_WEDGE = Q.pattern("interaction", "wedge3")
INTER_TRI = Q.pattern("interaction", "tri3")


def _signed_sql(ctes: str, q: Pattern, before: str, after: str) -> str:
    """Signed difference of the matches over two arc tables."""
    one = Q._matches(q, "true", "early").replace("FROM arcs", f"FROM {before}")
    two = Q._matches(q, "true", "late").replace("FROM arcs", f"FROM {after}")
    return f"{ctes}, {one}, {two} SELECT *, CAST(1 AS INTEGER) AS sign FROM (SELECT * FROM late EXCEPT SELECT * FROM early) UNION ALL SELECT *, CAST(-1 AS INTEGER) FROM (SELECT * FROM early EXCEPT SELECT * FROM late)"


_SLIDE = f"WITH e AS MATERIALIZED (SELECT *, ts <= TIMESTAMP '2024-01-20' AND ts > TIMESTAMP '2024-01-15' AS was, ts <= TIMESTAMP '2024-01-21' AND ts > TIMESTAMP '2024-01-16' AS now FROM ({INTER})), {_windowed("was")}, {_windowed('now')}"


@register("sliding_window_wedge", _signed_sql(_SLIDE, INTER_WEDGE, "arcs_was", "arcs_now"))
def sliding_window_wedge(s, d):
    g = build(s, d, "interaction")
    then = updates.window_by_time(g.edges, "2024-01-20", "5 days")
    state = prepare(PropertyGraph(g.vertices, then), INTER_WEDGE)
    return net(apply_batch(state, updates.slide(g.edges, "2024-01-20", "2024-01-21", "5 days"))[1])


_RELABEL = f"""WITH e AS MATERIALIZED (SELECT f.src, f.dst, f.elabel AS was, l.elabel AS now FROM ({INTER}) f JOIN (SELECT least(user_id, prev) AS src, greatest(user_id, prev) AS dst, arg_max(event_type, CAST(epoch_us(ts) AS HUGEINT) * 10000000 + event_id) AS elabel
 FROM (SELECT *, lag(user_id) OVER (ORDER BY ts, event_id) AS prev FROM events) WHERE prev <> user_id GROUP BY 1, 2) l USING (src, dst)),
 arcs_was AS MATERIALIZED (SELECT src, dst, was AS elabel FROM e UNION ALL SELECT dst, src, was FROM e), arcs_now AS MATERIALIZED (SELECT src, dst, now AS elabel FROM e UNION ALL SELECT dst, src, now FROM e)"""


def _relabelled(method: str):
    def run(s, d):
        g = build(s, d, "interaction")
        rows = builders.previous_user(builders.read(s, d, "events")).filter(F.col("previous").isNotNull() & (F.col("previous") != F.col("user_id")))
        last = rows.groupBy(F.least("user_id", "previous").alias("src"), F.greatest("user_id", "previous").alias("dst")).agg(F.max(F.struct("ts", "event_id", "event_type")).alias("l"))
        batch = updates.relabel(g.edges, last.select("src", "dst", F.col("l.event_type").alias("new")))
        return net(apply_batch(prepare(g, INTER_TRI, method), batch)[1])

    return run


for _method in ("direct_delta", "dag_index"):
    register(f"relabel_tri3_{_method}", _signed_sql(_RELABEL, INTER_TRI, "arcs_was", "arcs_now"))(_relabelled(_method))

_VERTEX = f"{CO}, arcs_kept AS MATERIALIZED (SELECT * FROM arcs WHERE src % 50 <> 0 AND dst % 50 <> 0)"


def _vertices_gone(insert: bool):
    def run(s, d):
        g = build(s, d, "copurchase")
        batch = updates.vertex_delete(g, g.vertices.filter("vid % 50 = 0").select("vid"))
        if not insert:
            return net(apply_batch(prepare(g, PATH, "tree_index"), batch)[1])
        without = g.edges.filter("src % 50 != 0 and dst % 50 != 0")
        return net(apply_batch(prepare(PropertyGraph(g.vertices, without), PATH, "bottomup_index"), updates.inserts(batch))[1])

    return run


register("vertex_delete_path4", _signed_sql(_VERTEX, PATH, "arcs", "arcs_kept"))(_vertices_gone(False))
register("vertex_insert_path4", _signed_sql(_VERTEX, PATH, "arcs_kept", "arcs"))(_vertices_gone(True))


@register("maintained_result_path4", Q.match_sql("copurchase", PATH))
def maintained_result(s, d):
    g, new = s90(s, d, "copurchase")
    state = prepare(g, PATH)
    arcs = state.arcs.now()
    before = cut(match(relations(arcs, PATH), PATH, orders.any_connected(PATH)), "result")
    return maintained(before, apply_batch(state, updates.inserts(new))[1])


# ---------------------------------------------------------------- candidates

_SIDES = [(u, w) for u, w, _ in PATH.edges]


def _dag_sql(tail: str) -> str:
    """Both passes of the DAG's index over the four-vertex path, whose highest DAG is rooted at vertex 0."""
    label = lambda u: f"SELECT vid FROM verts WHERE vlabel = '{PATH.vlabels[u]}'"
    near = lambda table: f"vid IN (SELECT src FROM arcs WHERE dst IN (SELECT vid FROM {table}))"
    up = ", ".join(f"up{u} AS MATERIALIZED ({label(u)}{f' AND {near(f"up{u - 1}")}' if u else ''})" for u in range(4))
    down = ", ".join(f"c{u} AS MATERIALIZED (SELECT vid FROM up{u}{f' WHERE {near(f"c{u + 1}")}' if u < 3 else ''})" for u in (3, 2, 1, 0))
    return f"{CO}, {up}, {down} {tail}"


_COUNTED = " UNION ALL ".join(f"SELECT {u} AS u, count(*) AS n_candidates FROM c{u}" for u in range(4))
Q.ORACLES["index_counts_dag"] = _dag_sql(_COUNTED)


def _dag_of(s, d):
    g = build(s, d, "copurchase")
    arcs = cut(g.arcs(), "arcs")
    return arcs, M.build_index("dag", PATH, arcs, g.vertices)


@register("label_candidates_edge", f"{CO} " + " UNION ALL ".join(
    f"SELECT {u} AS u, count(*) AS n_candidates FROM verts WHERE vlabel = '{PATH.vlabels[u]}'" + "".join(f" AND vid IN (SELECT a.src FROM arcs a JOIN verts v ON v.vid = a.dst WHERE v.vlabel = '{PATH.vlabels[w]}')" for w in PATH.neighbours(u)) for u in range(4)
))
def label_candidates_edge(s, d):
    g = build(s, d, "copurchase")
    return label_candidates(PATH, g.arcs(), g.vertices, "edge")


@register("implicit_candidates", _dag_sql(" UNION ALL ".join(f"SELECT {u} AS u, (SELECT count(*) FROM up{u}) - (SELECT count(*) FROM c{u}) AS n_implicit" for u in range(4))))
def implicit_candidates(s, d):
    flags = _dag_of(s, d)[1].flags()
    return flags.groupBy("u").agg(F.count(F.when(~F.col("down"), 1)).alias("n_implicit"))


@register("candidate_arcs", _dag_sql(" UNION ALL ".join(f"SELECT {e} AS q_edge, count(*) AS n FROM arcs WHERE src IN (SELECT vid FROM c{u}) AND dst IN (SELECT vid FROM c{w})" for e, (u, w) in enumerate(_SIDES))))
def candidate_arcs(s, d):
    arcs, ix = _dag_of(s, d)
    return ix.arcs(arcs).groupBy("q_edge").agg(F.count(F.lit(1)).alias("n"))


def _paths_sql() -> str:
    steps, out = "p0 AS (SELECT vid, CAST(1 AS HUGEINT) AS n FROM c0)", ["SELECT 0 AS u, CAST((SELECT count(*) FROM c0) AS BIGINT) AS n"]
    for u in (1, 2, 3):
        steps += f", p{u} AS (SELECT a.dst AS vid, sum(p.n) AS n FROM p{u - 1} p JOIN arcs a ON a.src = p.vid WHERE a.dst IN (SELECT vid FROM c{u}) GROUP BY 1)"
        out.append(f"SELECT {u}, CAST((SELECT sum(n) FROM p{u}) AS BIGINT)")
    return _dag_sql("").rstrip() + ", " + steps + " " + " UNION ALL ".join(out)


@register("path_counts", _paths_sql())
def path_counts(s, d):
    arcs, ix = _dag_of(s, d)
    return s.createDataFrame(sorted(ix.path_counts(arcs).items()), "u int, n long")


@register("relation_sizes_path4", f"{CO} " + " UNION ALL ".join(f"SELECT {e} AS q_edge, count(*) AS n FROM arcs JOIN verts x ON src = x.vid JOIN verts y ON dst = y.vid WHERE x.vlabel = '{PATH.vlabels[u]}' AND y.vlabel = '{PATH.vlabels[w]}'" for e, (u, w) in enumerate(_SIDES)))
def relation_sizes_path4(s, d):
    arcs = build(s, d, "copurchase").arcs()
    return reduce(DataFrame.unionByName, [relation(arcs, PATH, e).agg(F.count(F.lit(1)).alias("n")).select(F.lit(e).alias("q_edge"), "n") for e in range(PATH.m)])


# ---------------------------------------------------------------- streams

def _event_stream(s, d):
    """Events as a file stream; event times are points in time, as watermarks ask."""
    return s.readStream.schema(builders.read(s, d, "events").schema).parquet(f"{d}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def _finished(stream: DataFrame, mode: str) -> DataFrame:
    """All that a stream yields over what its source holds now, through a sink that a replay overwrites."""
    folder = f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    path = (lambda i: f"{folder}/out") if mode == "complete" else (lambda i: f"{folder}/out/batch_id={i}")
    sink = stream.writeStream.outputMode(mode).foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(path(i)))
    sink.option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    out = stream.sparkSession.read.schema(stream.schema).parquet(f"{folder}/out")
    return out.select(*[F.col(f.name).cast("timestamp_ntz").alias(f.name) if f.dataType.typeName() == "timestamp" else f.name for f in stream.schema])


def _streams():
    from graphdelta.streaming import runner

    register("stream_window_counts", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: _finished(runner.window_counts(_event_stream(s, d), "1 day"), "complete"))
    register("stream_sliding_counts", "SELECT start, event_type, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start, event_type FROM events) GROUP BY 1, 2")(
        lambda s, d: _finished(runner.window_counts(_event_stream(s, d), "2 hours", "1 hour"), "complete")
    )
    register(
        "stream_session_counts",
        "SELECT min(ts) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 1 HOUR THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, session",
    )(lambda s, d: _finished(runner.session_counts(_event_stream(s, d), "1 hour"), "complete"))

    @register("stream_temporal_wedge", "WITH k AS (SELECT *, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k FROM events) SELECT x.user_id AS a, x.k AS b, y.user_id AS c, x.ts AS t1, y.ts AS t2 FROM k x JOIN k y ON x.k = y.k AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE WHERE x.event_type = 'error' AND y.event_type = 'purchase'")
    def wedge(s, d):
        k = F.get_json_object("props", "$.k").cast("long")
        errors = _event_stream(s, d).filter("event_type = 'error'").select(F.col("user_id").alias("src"), k.alias("dst"), "ts")
        buys = _event_stream(s, d).filter("event_type = 'purchase'").select(k.alias("src"), F.col("user_id").alias("dst"), "ts")
        return _finished(runner.temporal_wedge(errors, buys, "10 minutes"), "append")

    @register("stream_interaction_wedge", Q.delta_sql("interaction", INTER_WEDGE))
    def stream_matches(s, d):
        g, new = s90(s, d, "interaction")
        folder = f"{shared_dir(s)}/updates-{uuid.uuid4().hex}"
        half = new.filter("src % 2 = 0"), new.filter("src % 2 = 1")
        for part in half:  # two files, one a trigger
            updates.inserts(part).withColumn("seq", F.lit(0).cast("long")).coalesce(1).write.mode("append").parquet(folder)
        runs = runner.StreamMatcher(g, INTER_WEDGE, f"{folder}-run")
        runs.run(runner.file_updates(s, folder))
        return net(runs.matches(s).drop("batch_id"))

    @register("stream_user_activity", "SELECT user_id AS key, count(*) AS n, min(ts) AS first, max(ts) AS last FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL GROUP BY 1")
    def user_activity(s, d):
        folder = f"{shared_dir(s)}/events-{uuid.uuid4().hex}"
        events = builders.read(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
        for i in range(3):  # three files, one a trigger, so that state is carried on
            events.filter(F.pmod("event_id", F.lit(3)) == i).coalesce(1).write.mode("append").parquet(folder)
        stream = s.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
        every = _finished(runner.activity(stream, "user_id"), "update")
        return every.groupBy("key").agg(F.max_by(F.struct("n", "first", "last"), "n").alias("x")).select("key", "x.*")

    @register(
        "stream_late_edges",
        f"WITH e AS ({INTER}), p AS (SELECT CAST(src % 3 AS INTEGER) AS batch_id, ts FROM e), t AS (SELECT batch_id, max(ts) AS top FROM p GROUP BY 1)"
        " SELECT t.batch_id, (SELECT count(*) FROM p WHERE p.batch_id = t.batch_id AND p.ts < (SELECT max(top) FROM t x WHERE x.batch_id < t.batch_id) - INTERVAL 7 DAY) AS n_late FROM t",
    )
    def late_edges(s, d):
        g = build(s, d, "interaction")
        folder = f"{shared_dir(s)}/updates-{uuid.uuid4().hex}"
        for i in range(3):
            rows = g.edges.filter(F.pmod("src", F.lit(3)) == i).withColumn("ts", F.col("ts").cast("timestamp"))
            updates.inserts(rows).withColumn("seq", F.lit(0).cast("long")).coalesce(1).write.mode("append").parquet(folder)
        nothing = PropertyGraph(g.vertices, g.edges.limit(0).withColumn("ts", F.col("ts").cast("timestamp")))
        runs = runner.StreamMatcher(nothing, INTER_WEDGE, f"{folder}-run", late=7 * 86_400)
        runs.run(runner.file_updates(s, folder))
        return runs.watermark.marks(s).select("batch_id", "n_late")


_streams()
