"""The registered queries of the engine, and the SQL each is held against.

The SQL recomputes: it joins the pattern over the old and over the new edges and takes EXCEPT, never the telescoped
terms.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdelta.index.candidates import label_candidates
from graphdelta.methods import matchers as M
from graphdelta.methods.advise import advise
from graphdelta.metrics import measures
from graphdelta.operators.extend import edge_join, match
from graphdelta.pattern.model import Pattern, parse
from graphdelta.plans import orders
from graphdelta.plans.relations import relations
from graphdelta.sources import builders, stats, updates
from graphdelta.sources.graph import PropertyGraph, numbered, split_hash, split_stream
from graphdelta.sources.storage import cut

TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
EVENTS = ["click", "view", "error", "signup", "purchase"]
SHAPES = {
    "wedge3": "01 12",
    "tri3": "01 12 02",
    "path4": "01 12 23",
    "square4": "01 12 23 03",
    "diamond4": "01 12 23 03 02",
    "clique4": "01 02 03 12 13 23",
    "tree6": "01 02 13 14 25",
    "sparse6": "01 12 23 34 45 24 35",
    "dense6": "01 02 03 04 05 12 13 14 23 24",
}


def pattern(graph: str, name: str) -> Pattern:
    """A named shape with the labels of a graph."""
    n = 1 + max(int(c) for c in SHAPES[name].replace(" ", ""))
    if graph == "copurchase":
        return parse(SHAPES[name], [TYPES[i % 6] for i in range(n)], None, name)
    if graph == "cobrand":
        return parse(SHAPES[name], [f"Brand#{1 + 3 * i % 25}" for i in range(n)], None, name)
    return parse(SHAPES[name], [None] * n, [EVENTS[k % 5] for k in range(len(SHAPES[name].split()))], name)


#: O order, C customer, P part, S supplier, N nation; all vertices bear one label.
COMMERCE = {
    "c_tri": Pattern((None,) * 3, ((0, 1, "OP:NO"), (0, 2, "OS:NO"), (1, 2, "PS:ECONOMY")), "c_tri"),
    "c_path": Pattern((None,) * 4, ((0, 1, "CO:F:1"), (1, 2, "OP:RF"), (2, 3, "PS:PROMO")), "c_path"),
    "c_square": Pattern((None,) * 4, ((0, 1, "CN:BUILDING"), (1, 2, "SN"), (2, 3, "OS:RF"), (0, 3, "CO:F:1")), "c_square"),
    "c_two_lines": Pattern((None,) * 5, ((0, 1, "OP:NO"), (0, 2, "OS:NO"), (1, 2, "PS:ECONOMY"), (0, 3, "OP:NO"), (0, 4, "OS:NO"), (3, 4, "PS:ECONOMY"), (1, 4, "PS:ECONOMY")), "c_two_lines"),
}


def named(graph: str, name: str) -> Pattern:
    return COMMERCE[name] if graph == "commerce" else pattern(graph, name)


def build(spark, d: str, graph: str) -> PropertyGraph:
    """A graph whose tables are written once, as a stream of updates would find them."""
    g = builders.GRAPHS[graph](spark, d)
    return PropertyGraph(cut(g.vertices), cut(g.edges))


def s90(spark, d: str, graph: str, rate: float = 0.1):
    g = build(spark, d, graph)
    old, new = split_stream(g.edges, rate)
    return PropertyGraph(g.vertices, old), new


# ---------------------------------------------------------------- SQL of the graphs

_CONSECUTIVE = """SELECT least(a.p, b.p) AS src, greatest(a.p, b.p) AS dst, 'co' AS elabel, min(o.o_orderdate) AS ts
 FROM (SELECT DISTINCT l_orderkey AS k, l_linenumber AS n, l_partkey AS p FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey AS k, l_linenumber AS n, l_partkey AS p FROM lineitem) b
 ON a.k = b.k AND b.n = a.n + 1 AND a.p <> b.p JOIN orders o ON o.o_orderkey = a.k GROUP BY 1, 2"""
_INTERACTION = """SELECT src, dst, elabel, ts FROM (SELECT least(user_id, prev) AS src, greatest(user_id, prev) AS dst, {label} AS elabel, ts,
 row_number() OVER (PARTITION BY least(user_id, prev), greatest(user_id, prev) ORDER BY ts, event_id) AS n
 FROM (SELECT *, lag(user_id) OVER (ORDER BY ts, event_id) AS prev FROM events) WHERE prev <> user_id) WHERE n = 1"""
_COMMERCE = """SELECT src, dst, elabel, ts FROM (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY ts, elabel) AS n FROM (
 SELECT least(a, b) AS src, greatest(a, b) AS dst, elabel, ts FROM (
  SELECT o_custkey * 10 AS a, o_orderkey * 10 + 1 AS b, 'CO:' || o_orderstatus || ':' || substr(o_orderpriority, 1, 1) AS elabel, CAST(o_orderdate AS TIMESTAMP) AS ts FROM orders
  UNION ALL SELECT l_orderkey * 10 + 1, l_partkey * 10 + 2, 'OP:' || l_returnflag || l_linestatus, CAST(l_shipdate AS TIMESTAMP) FROM lineitem
  UNION ALL SELECT l_orderkey * 10 + 1, l_suppkey * 10 + 3, 'OS:' || l_returnflag || l_linestatus, CAST(l_shipdate AS TIMESTAMP) FROM lineitem
  UNION ALL SELECT l_partkey * 10 + 2, l_suppkey * 10 + 3, 'PS:' || p_type, CAST(l_shipdate AS TIMESTAMP) FROM lineitem JOIN part ON l_partkey = p_partkey
  UNION ALL SELECT c_custkey * 10, CAST(c_nationkey AS BIGINT) * 10 + 4, 'CN:' || c_mktsegment, TIMESTAMP '1970-01-01' FROM customer
  UNION ALL SELECT s_suppkey * 10 + 3, CAST(s_nationkey AS BIGINT) * 10 + 4, 'SN', TIMESTAMP '1970-01-01' FROM supplier
  UNION ALL SELECT CAST(n_nationkey AS BIGINT) * 10 + 4, CAST(n_regionkey AS BIGINT) * 10 + 5, 'NR', TIMESTAMP '1970-01-01' FROM nation) WHERE a <> b)) WHERE n = 1"""
EDGES_SQL = {
    "copurchase": _CONSECUTIVE,
    "cobrand": _CONSECUTIVE,
    "interaction": _INTERACTION.format(label="event_type"),
    "interaction_skew": _INTERACTION.format(label="CASE WHEN value < 61.5 THEN 'main' ELSE event_type END"),
    "commerce": _COMMERCE,
}
VERTICES_SQL = {
    "copurchase": "SELECT p_partkey AS vid, p_type AS vlabel FROM part",
    "cobrand": "SELECT p_partkey AS vid, p_brand AS vlabel FROM part",
    "interaction": "SELECT DISTINCT user_id AS vid, 'user' AS vlabel FROM events",
    "commerce": "SELECT DISTINCT unnest([src, dst]) AS vid, 'any' AS vlabel FROM edges",
}


def _base(graph: str, share: str = "0.9") -> str:
    return f"""WITH edges AS MATERIALIZED ({EDGES_SQL[graph]}),
 ranked AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY ts, src, dst) AS rn, count(*) OVER () AS total FROM edges),
 verts AS MATERIALIZED ({VERTICES_SQL[graph]}),
 arcs AS MATERIALIZED (SELECT src, dst, elabel, rn <= floor({share} * total) AS old FROM ranked UNION ALL SELECT dst, src, elabel, rn <= floor({share} * total) FROM ranked)"""


def _matches(q: Pattern, where: str, name: str, semantics: str = "iso") -> str:
    """CTE of all matches over the arcs that satisfy ``where``; injectivity in an outer filter."""
    cols = {}
    tables, conds = [], []
    for e, (u, w, label) in enumerate(q.edges):
        tables.append(f"(SELECT src, dst, elabel FROM arcs WHERE {where}) r{e}")
        if label is not None:
            conds.append(f"r{e}.elabel = '{label}'")
        for v, side in ((u, "src"), (w, "dst")):
            if v in cols:
                conds.append(f"{cols[v]} = r{e}.{side}")
            else:
                cols[v] = f"r{e}.{side}"
    for v, label in enumerate(q.vlabels):
        if label is not None:
            tables.append(f"(SELECT vid FROM verts WHERE vlabel = '{label}') v{v}")
            conds.append(f"{cols[v]} = v{v}.vid")
    names = ", ".join(f"{cols[v]} AS m{v}" for v in range(q.n))
    differ = " AND ".join(f"m{a} <> m{b}" for a in range(q.n) for b in range(a + 1, q.n)) if semantics == "iso" else "true"
    return f"{name}_all AS MATERIALIZED (SELECT {names} FROM {', '.join(tables)} WHERE {' AND '.join(conds)}), {name} AS (SELECT * FROM {name}_all WHERE {differ})"


def match_sql(graph: str, q: Pattern, semantics: str = "iso") -> str:
    return f"{_base(graph)}, {_matches(q, 'true', 'hit', semantics)} SELECT * FROM hit"


def delta_sql(graph: str, q: Pattern, semantics: str = "iso", sign: int = 1, share: str = "0.9") -> str:
    """Matches that the last edges, a tenth of them unless told otherwise, add (or, deleted again, take away)."""
    return f"{_base(graph, share)}, {_matches(q, 'true', 'late', semantics)}, {_matches(q, 'old', 'early', semantics)} SELECT *, CAST({sign} AS INTEGER) AS sign FROM (SELECT * FROM late EXCEPT SELECT * FROM early)"


# ---------------------------------------------------------------- queries

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def take(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return take


def _delta(graph: str, method: str, shape: str, semantics: str = "iso", rate: float = 0.1):
    def run(spark, d):
        g, new = s90(spark, d, graph, rate)
        return M.run_method(method, updates.insertion(g, new), named(graph, shape), g.vertices, semantics)

    return run


def _deleted(graph: str, method: str, shape: str):
    def run(spark, d):
        g = build(spark, d, graph)
        _, last = split_stream(g.edges)
        return M.run_method(method, updates.deletion(g, last), named(graph, shape), g.vertices)

    return run


def _static(graph: str, shape: str, semantics: str, strategy: str = "first"):
    def run(spark, d):
        g = build(spark, d, graph)
        q = named(graph, shape)
        arcs = cut(g.arcs())
        return match(relations(arcs, q), q, orders.order_static(q, stats.relation_sizes(arcs, q)), semantics, strategy)

    return run


def _fill() -> None:
    for graph in ("copurchase", "cobrand", "interaction", "interaction_skew", "commerce"):
        register(f"{graph}_edges", EDGES_SQL[graph])(lambda s, d, graph=graph: builders.GRAPHS[graph](s, d).edges)
    register("similarity_edges")(lambda s, d: builders.similarity(s, d).edges)
    for graph in ("copurchase", "interaction", "commerce"):
        q = f"WITH edges AS ({EDGES_SQL[graph]}), deg AS (SELECT vid, count(*) AS degree FROM (SELECT unnest([src, dst]) AS vid FROM edges) GROUP BY vid), lab AS (SELECT elabel, count(*) AS c FROM edges GROUP BY elabel)"
        register(
            f"graph_stats_{graph}",
            f"{q} SELECT (SELECT count(*) FROM deg) AS n_vertices, (SELECT count(*) FROM edges) AS n_edges, (SELECT count(*) FROM lab) AS n_elabels, round(2.0 * (SELECT count(*) FROM edges) / (SELECT count(*) FROM deg), 4) AS avg_degree, (SELECT max(degree) FROM deg) AS max_degree, round(CAST((SELECT max(c) FROM lab) AS DOUBLE) / (SELECT count(*) FROM edges), 4) AS top_label_share",
        )(lambda s, d, graph=graph: stats.graph_stats(build(s, d, graph).edges))
        register(f"label_histogram_{graph}", f"{q} SELECT elabel, c AS n_edges FROM lab")(lambda s, d, graph=graph: stats.label_histogram(build(s, d, graph).edges))
        register(f"split_stream_{graph}", f"{_base(graph)} SELECT src, dst, elabel, ts, CAST(rn > floor(0.9 * total) AS INTEGER) AS late FROM ranked")(
            lambda s, d, graph=graph: reduce(DataFrame.unionByName, [e.withColumn("late", F.lit(i)) for i, e in enumerate(split_stream(build(s, d, graph).edges))])
        )
    co = f"WITH edges AS ({EDGES_SQL['copurchase']}), deg AS (SELECT vid, count(*) AS degree FROM (SELECT unnest([src, dst]) AS vid FROM edges) GROUP BY vid)"
    register("degree_distribution", f"{co} SELECT degree, count(*) AS n_vertices FROM deg GROUP BY degree")(lambda s, d: stats.degree_distribution(build(s, d, "copurchase").edges))
    register("hub_topk", f"{co} SELECT vid, degree FROM deg ORDER BY degree DESC, vid LIMIT 20")(lambda s, d: stats.hub_topk(build(s, d, "copurchase").edges, 20))
    register("split_stream_hash", f"{co} SELECT src, dst, CAST((src * 31 + dst * 17) % 10 = 0 AS INTEGER) AS late FROM edges")(
        lambda s, d: reduce(DataFrame.unionByName, [e.select("src", "dst", F.lit(i).alias("late")) for i, e in enumerate(split_hash(build(s, d, "copurchase").edges))])
    )
    register("khop_2", f"WITH edges AS ({EDGES_SQL['copurchase']}), a AS (SELECT src, dst FROM edges UNION ALL SELECT dst, src FROM edges), h1 AS (SELECT DISTINCT dst AS vid FROM a WHERE src = 1), h2 AS (SELECT DISTINCT a.dst AS vid FROM h1 JOIN a ON a.src = h1.vid) SELECT vid, CAST(min(h) AS INTEGER) AS hop FROM (SELECT CAST(1 AS BIGINT) AS vid, 0 AS h UNION ALL SELECT vid, 1 FROM h1 UNION ALL SELECT vid, 2 FROM h2) GROUP BY vid")(
        lambda s, d: stats.khop(build(s, d, "copurchase").arcs(), s.range(1, 2).withColumnRenamed("id", "vid"), 2)
    )
    register("kcore_copurchase")(lambda s, d: stats.core_numbers(build(s, d, "copurchase").edges))

    for shape in ("wedge3", "tri3", "path4", "square4", "diamond4", "clique4", "tree6", "sparse6", "dense6"):
        register(f"match_{shape}", match_sql("copurchase", pattern("copurchase", shape)))(_static("copurchase", shape, "iso"))
    for shape in ("wedge3", "path4"):
        register(f"match_{shape}_hom", match_sql("interaction", pattern("interaction", shape), "hom"))(_static("interaction", shape, "hom"))
    register("match_square4_least_first", match_sql("copurchase", pattern("copurchase", "square4")))(_static("copurchase", "square4", "iso", "least"))

    def edge_at_a_time(s, d):
        q = pattern("copurchase", "square4")
        arcs = cut(build(s, d, "copurchase").arcs())
        return edge_join(relations(arcs, q), q, orders.order_edges(q, stats.relation_sizes(arcs, q)))

    register("match_square4_edge_join", match_sql("copurchase", pattern("copurchase", "square4")))(edge_at_a_time)

    for method in M.METHODS:
        for shape in ("path4", "tri3", "square4"):
            if method.startswith("bottomup") and shape != "path4":
                continue
            # recomputation edge by edge of the triangle and the square gets a batch of one in two hundred edges
            rate, share = (0.005, "0.995") if method == "local_recompute" and shape != "path4" else (0.1, "0.9")
            register(f"delta_{method}_{shape}", delta_sql("copurchase", pattern("copurchase", shape), share=share))(_delta("copurchase", method, shape, rate=rate))
    for method, shape in (("direct_delta", "tree6"), ("direct_delta", "sparse6"), ("direct_delta", "dense6"), ("dag_index", "sparse6"), ("tree_index", "tree6"), ("bottomup_index", "tree6")):
        register(f"delta_{method}_{shape}", delta_sql("copurchase", pattern("copurchase", shape)))(_delta("copurchase", method, shape))
    for graph, shape in (("cobrand", "tri3"), ("interaction", "path4"), ("commerce", "c_tri"), ("commerce", "c_path"), ("commerce", "c_square"), ("commerce", "c_two_lines")):
        register(f"delta_direct_{graph}_{shape}", delta_sql(graph, named(graph, shape)))(_delta(graph, "direct_delta", shape))
    register("delta_dag_commerce_c_tri", delta_sql("commerce", COMMERCE["c_tri"]))(_delta("commerce", "dag_index", "c_tri"))
    register("delta_direct_two_lines_hom", delta_sql("commerce", COMMERCE["c_two_lines"], "hom"))(_delta("commerce", "direct_delta", "c_two_lines", "hom"))
    for method in ("full_recompute", "direct_delta", "tree_index", "dag_index", "bottomup_index"):
        register(f"delete_{method}_path4", delta_sql("copurchase", pattern("copurchase", "path4"), sign=-1))(_deleted("copurchase", method, "path4"))

    @register("static_snapshot_net_change", delta_sql("copurchase", pattern("copurchase", "diamond4")))
    def net(s, d):
        g, new = s90(s, d, "copurchase")
        change = updates.insertion(g, new)
        return M.static_snapshot(change.rest, change.full, pattern("copurchase", "diamond4"))

    tri = pattern("copurchase", "tri3")

    @register(
        "mixed_batch_tri3",
        f"""{_base('copurchase')}, mixed AS MATERIALIZED (SELECT src, dst, elabel, rn, rn > floor(0.9 * total) AS is_new, rn <= floor(0.05 * total) AS is_gone FROM ranked),
 arcs2 AS MATERIALIZED (SELECT src, dst, elabel, NOT is_new AS before, NOT is_gone AS after FROM mixed UNION ALL SELECT dst, src, elabel, NOT is_new, NOT is_gone FROM mixed),
 {_matches(tri, 'after', 'late').replace('FROM arcs', 'FROM arcs2')}, {_matches(tri, 'before', 'early').replace('FROM arcs', 'FROM arcs2')}
 SELECT *, CAST(1 AS INTEGER) AS sign FROM (SELECT * FROM late EXCEPT SELECT * FROM early) UNION ALL SELECT *, CAST(-1 AS INTEGER) FROM (SELECT * FROM early EXCEPT SELECT * FROM late)""",
    )
    def mixed(s, d):
        g, new = s90(s, d, "copurchase")
        total = g.edges.count() + new.count()
        gone = numbered(g.edges, "ts", "src", "dst").filter(F.col("n") < int(total * 0.05)).drop("n")
        minus, plus, _ = updates.mixed(g, updates.inserts(new).unionByName(updates.deletes(gone)))
        signed = M.direct_delta(minus, tri).unionByName(M.direct_delta(plus, tri))
        cols = [c for c in signed.columns if c != "sign"]
        return signed.groupBy(*cols).agg(F.sum("sign").cast("int").alias("sign")).filter("sign != 0")

    path = pattern("copurchase", "path4")
    labelled = " UNION ALL ".join(f"SELECT {u} AS u, count(*) AS n_candidates FROM verts WHERE vlabel = '{label}'" for u, label in enumerate(path.vlabels))
    register("label_candidates_vertex", f"{_base('copurchase')} {labelled}")(lambda s, d: label_candidates(path, (g := build(s, d, "copurchase")).arcs(), g.vertices))
    for index in ("tree", "dag", "bottomup"):

        def counted(s, d, index=index):
            g = build(s, d, "copurchase")
            return M.build_index(index, path, cut(g.arcs()), g.vertices).counts()

        # root 0: a path from the first vertex; the others differ by where the root lies
        register(f"index_counts_{index}", _path_counts_sql(index))(counted)

    @register("index_updated_equals_rebuilt", "SELECT CAST(0 AS BIGINT) AS n_different")
    def same(s, d):
        g, new = s90(s, d, "copurchase")
        change = updates.insertion(g, new)
        old = M.build_index("dag", tri, change.rest, g.vertices)
        a, b = old.updated(change).flags(), M.build_index("dag", tri, change.full, g.vertices).flags()
        return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("n_different"))

    @register("index_audit", "SELECT CAST(0 AS BIGINT) AS n_missing")
    def audit(s, d):
        g = build(s, d, "copurchase")
        arcs = cut(g.arcs())
        found = match(relations(arcs, tri), tri, orders.any_connected(tri), "hom")
        return M.build_index("dag", tri, arcs, g.vertices).audit(found, arcs).agg(F.count(F.lit(1)).alias("n_missing"))

    @register("count_tree_hom_path4", f"{_base('copurchase')}, {_matches(path, 'true', 'hit', 'hom')} SELECT CAST(count(*) AS BIGINT) AS n_matches FROM hit")
    def tree_hom(s, d):
        g = build(s, d, "copurchase")
        return M.count_tree_hom(path, cut(g.arcs()), g.vertices)

    @register("partials_by_depth")
    def partials(s, d):
        g, new = s90(s, d, "copurchase")
        return measures.depth_counters(updates.insertion(g, new), path, lambda k, x, y: orders.order_direct(path, (x, y)))

    @register("adaptive_partials")
    def adaptive(s, d):
        g, new = s90(s, d, "copurchase")
        change = updates.insertion(g, new)
        ix = M.current_index("dag", change, tri, g.vertices)
        return measures.adaptive_partials(ix.pruned(change), tri)

    @register("bottomup_dead_ends", "SELECT CAST(0 AS BIGINT) AS dead_empty")
    def dead(s, d):
        g, new = s90(s, d, "copurchase")
        change = updates.insertion(g, new)
        ix, parts = M.build_index("bottomup", path, change.base, g.vertices), []
        for k in range(path.m):
            levels: list[DataFrame] = []
            last = M.bottomup_term(ix, change, k, "hom", seen=lambda depth, k, rows, grown: levels.append(rows))  # noqa: B023
            for rows, next_rows in zip(levels, [*levels[1:], last], strict=True):
                parts.append(rows.join(next_rows.select(*rows.columns).distinct(), rows.columns, "left_anti").agg(F.count(F.lit(1)).alias("n")))
            ix = ix.updated(change, k)
        return reduce(DataFrame.unionByName, parts).agg(F.sum("n").alias("dead_empty"))

    @register("advise_table", _advise_sql())
    def advice(s, d):
        degree = stats.graph_stats(build(s, d, "copurchase").edges).first()["avg_degree"]
        rows = [(name, q.density_class, *advise(q, degree or 0.0), degree) for name, q in ((n, pattern("copurchase", n)) for n in sorted(SHAPES))]
        return s.createDataFrame(rows, "pid string, kind string, index_choice string, order_choice string, avg_degree double")

    register("early_stop_10")(lambda s, d: M.direct_delta((c := _change(s, d)), path, limit=10))
    register("window_count_500", f"WITH edges AS ({EDGES_SQL['copurchase']}) SELECT * FROM edges ORDER BY ts DESC, src DESC, dst DESC LIMIT 500")(lambda s, d: updates.window_by_count(build(s, d, "copurchase").edges, 500))
    register("window_time_30d", f"WITH edges AS ({EDGES_SQL['copurchase']}) SELECT * FROM edges WHERE ts <= TIMESTAMP '1998-01-01' AND ts > TIMESTAMP '1997-12-02'")(
        lambda s, d: updates.window_by_time(build(s, d, "copurchase").edges, "1998-01-01 00:00:00", "30 days")
    )
    register("batch_sizes_100", f"{_base('copurchase')} SELECT CAST(floor((rn - floor(0.9 * total) - 1) / 100) AS BIGINT) AS batch_id, count(*) AS n FROM ranked WHERE rn > floor(0.9 * total) GROUP BY 1")(
        lambda s, d: updates.batches(s90(s, d, "copurchase")[1], 100).groupBy("batch_id").agg(F.count(F.lit(1)).alias("n"))
    )
    register("cube_stream", f"{_base('copurchase')} SELECT vlabel, CAST(rn > floor(0.9 * total) AS INTEGER) AS late, count(*) AS n FROM ranked JOIN verts ON src = vid GROUP BY CUBE (vlabel, CAST(rn > floor(0.9 * total) AS INTEGER))")(_cube)


def _change(s, d):
    g, new = s90(s, d, "copurchase")
    return updates.insertion(g, new)


def _cube(s, d):
    g, new = s90(s, d, "copurchase")
    both = g.edges.withColumn("late", F.lit(0)).unionByName(new.withColumn("late", F.lit(1)))
    return both.join(g.vertices, F.col("src") == F.col("vid")).cube("vlabel", "late").agg(F.count(F.lit(1)).alias("n"))


def _path_counts_sql(index: str) -> str | None:
    """Candidates of the four-vertex path by definition; only the bottom-up index has a root that SQL knows beforehand."""
    if index != "bottomup":
        return None
    q = pattern("copurchase", "path4")
    out = f"{_base('copurchase')}, c3 AS (SELECT vid FROM verts WHERE vlabel = '{q.vlabels[3]}')"
    for u in (2, 1, 0):
        out += f", c{u} AS (SELECT vid FROM verts WHERE vlabel = '{q.vlabels[u]}' AND vid IN (SELECT src FROM arcs WHERE dst IN (SELECT vid FROM c{u + 1})))"
    return out + " " + " UNION ALL ".join(f"SELECT {u} AS u, count(*) AS n_candidates FROM c{u}" for u in range(4))


def _advise_sql() -> str:
    """Advice by shape and by the average degree of the co-purchase graph, over vertices with an edge."""
    rows = []
    for name in sorted(SHAPES):
        q = pattern("copurchase", name)
        degree = 2 * q.m / q.n
        kind = "tree" if q.m == q.n - 1 else "sparse" if degree <= 3 else "dense"
        rows.append(f"('{name}', '{kind}')")
    return f"""WITH edges AS MATERIALIZED ({EDGES_SQL['copurchase']}),
 s AS (SELECT round(2.0 * count(*) / nullif((SELECT count(DISTINCT vid) FROM (SELECT unnest([src, dst]) AS vid FROM edges)), 0), 4) AS avg_degree FROM edges)
 SELECT pid, kind, CASE WHEN kind = 'sparse' THEN 'dag' ELSE 'none' END AS index_choice,
 CASE WHEN kind = 'tree' THEN 'bottomup' WHEN kind = 'dense' OR coalesce(avg_degree, 0) <= 4 THEN 'direct' ELSE 'dag' END AS order_choice, avg_degree
 FROM (VALUES {', '.join(rows)}) t(pid, kind), s"""


_fill()


@register(
    "distinct_tri3_subgraphs",
    f"{_base('interaction')}, {_matches(Pattern((None,) * 3, ((0, 1, None), (1, 2, None), (0, 2, None))), 'true', 'hit')} SELECT count(*) // 6 AS n_subgraphs FROM hit",
)
def _distinct(s, d):
    from graphdelta.functions.sql import distinct_subgraphs

    q = Pattern((None,) * 3, ((0, 1, None), (1, 2, None), (0, 2, None)))
    arcs = cut(build(s, d, "interaction").arcs())
    return distinct_subgraphs(match(relations(arcs, q), q, orders.any_connected(q)), 3).agg(F.count(F.lit(1)).alias("n_subgraphs"))
