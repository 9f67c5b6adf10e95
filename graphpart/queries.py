"""Queries over the given tables, and the SQL that says the same."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphpart.functions.draws import draw_sql
from graphpart.operators import adapt, apps, baselines, bounds, convert, metrics, migrate, placement, scores
from graphpart.operators import state as st
from graphpart.operators.engine import FixedIterations, PartitionResult, partition
from graphpart.plans.graph_sql import GRAPH_SQL
from graphpart.plans.oracle import Loop, smallworld_sql
from graphpart.session import durable, shared_folder
from graphpart.sources import graphs
from graphpart.sources.tables import load
from graphpart.streaming import adaptive
from graphpart.workloads import experiments

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}
K, SEED = 8, 42
PORTABLE = "portable"
FULL = 16  # iterations at most of the queries on the larger graphs that show the way to a halt
TO_HALT = ("g_web", "g_conv")  # graphs whose queries run until the rule halts them


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


# -- graphs

for _name, _build in graphs.BUILDERS.items():
    query(_name.replace("g_", "graph_", 1), GRAPH_SQL[_name])(_build)

query("graph_smallworld", smallworld_sql("SELECT c_custkey AS key FROM customer", 4, 0.3))(lambda s, d: graphs.small_world_of(load(s, d, "customer").select(F.col("c_custkey").alias("key")), 4, 0.3, SEED, PORTABLE))


def _e(name: str) -> str:
    return f"SELECT src, dst FROM ({GRAPH_SQL[name]})"


def _arcs_sql(name: str, directed: bool) -> str:
    w = "count(*)" if directed else "1"
    return f"SELECT src, dst, CAST({w} AS INTEGER) AS w FROM (SELECT DISTINCT src, dst, side FROM (SELECT src, dst, 0 AS side FROM ({_e(name)}) UNION ALL SELECT dst, src, 1 FROM ({_e(name)})) WHERE src <> dst) GROUP BY src, dst"


def _graph(name: str) -> Query:
    return lambda s, d: graphs.BUILDERS[name](s, d).select("src", "dst")


for _name in ("g_events", "g_knn", "g_web"):
    query(f"sym_weighted_{_name[2:]}", _arcs_sql(_name, True))(lambda s, d, g=_name: convert.to_weighted_undirected(_graph(g)(s, d)))
query("sym_naive_events", _arcs_sql("g_events", False))(lambda s, d: convert.to_undirected(_graph("g_events")(s, d)))
_LINES = "SELECT l_partkey * 8 + 2 AS src, l_suppkey * 8 + 1 AS dst FROM lineitem"
query("sym_multiplicity_lines", f"SELECT src, dst, CAST(count(*) AS INTEGER) AS w FROM ({_LINES} UNION ALL SELECT dst, src FROM ({_LINES})) GROUP BY src, dst")(
    lambda s, d: convert.to_weighted_undirected(load(s, d, "lineitem").select((F.col("l_partkey") * 8 + 2).alias("src"), (F.col("l_suppkey") * 8 + 1).alias("dst")), weights="multiplicity")
)
query("reciprocity", f"WITH e AS ({_e('g_events')}) SELECT count(*) AS edges, count(*) FILTER (WHERE EXISTS (SELECT 1 FROM e b WHERE b.src = e.dst AND b.dst = e.src)) AS reciprocal FROM e")(
    lambda s, d: convert.reciprocity(_graph("g_events")(s, d))
)
query(
    "convert_messages",
    f"WITH e AS ({_e('g_events')}), x AS (SELECT e.src, EXISTS (SELECT 1 FROM e b WHERE b.src = e.dst AND b.dst = e.src) AS r FROM e) SELECT count(*) AS messages, count(*) FILTER (WHERE r) AS raised, count(*) FILTER (WHERE NOT r) AS created FROM x",
)(lambda s, d: convert.convert_with_cost(_graph("g_events")(s, d))[1])
query("degree_stats", f"WITH a AS ({_arcs_sql('g_cust_supp', False)}), v AS (SELECT src, count(*) AS deg FROM a GROUP BY src) SELECT CAST(sum(deg) AS BIGINT) AS arcs, count(*) AS vertices, min(deg) AS min_deg, round(avg(deg), 6) AS mean_deg, max(deg) AS max_deg FROM v")(
    lambda s, d: convert.degree_stats(convert.to_undirected(_graph("g_cust_supp")(s, d)))
)
query("feasible_k", f"WITH a AS ({_arcs_sql('g_cust_supp', False)}), v AS (SELECT src, count(*) AS deg FROM a GROUP BY src) SELECT CAST(floor(CAST(1.05 AS DOUBLE) * sum(deg) / max(deg)) AS BIGINT) AS k_max FROM v")(
    lambda s, d: convert.feasible_k(convert.to_undirected(_graph("g_cust_supp")(s, d)))
)
query("top_hubs", f"WITH a AS ({_arcs_sql('g_cust_supp', False)}) SELECT src AS v, count(*) AS deg FROM a GROUP BY src ORDER BY deg DESC, v LIMIT 10")(lambda s, d: metrics.top_hubs(convert.to_undirected(_graph("g_cust_supp")(s, d))))
query("typed_ids", "SELECT c_custkey * 8 AS v, c_custkey AS key, 0 AS kind FROM customer")(
    lambda s, d: load(s, d, "customer").select(graphs.encode_id(F.col("c_custkey"), "customer").alias("v")).select("v", graphs.decode_id(F.col("v")).alias("x")).select("v", "x.key", "x.kind")
)

# -- pieces of an iteration, on g_events (directed) with k = 8

_LOOP = Loop(_e("g_events"), K, 1)


def _pieces(s: SparkSession, d: str) -> dict[str, DataFrame | float]:
    arcs = convert.to_weighted_undirected(_graph("g_events")(s, d))
    verts = convert.vertex_stats(arcs)
    labels = st.init_random(verts, K, SEED, PORTABLE)
    state = verts.join(labels, "v")
    total = verts.agg(F.sum("deg")).first()[0] or 0
    cap = st.capacity(total, K)
    loads = st.partition_loads(state, label_set=list(range(K)))
    return {"arcs": arcs, "verts": verts, "labels": labels, "state": state, "cap": cap, "loads": loads}


def _scored(p: dict, kind: str = "all_k") -> DataFrame:
    return scores.score_balanced(scores.build_hist(p["arcs"], p["labels"]), p["state"], p["loads"], p["cap"], kind)


query("vertex_stats", _LOOP.sql("SELECT v, deg, wdeg FROM verts"))(lambda s, d: _pieces(s, d)["verts"])
query("init_random", _LOOP.sql("SELECT v, label FROM lab0"))(lambda s, d: _pieces(s, d)["labels"])
query("hist", _LOOP.sql("SELECT v, label, h FROM h1"))(lambda s, d: (p := _pieces(s, d)) and scores.build_hist(p["arcs"], p["labels"]).select("v", "label", "h"))
query("score_count", _LOOP.sql("SELECT a.dst AS v, l.label, count(*) AS score FROM arcs a JOIN lab0 l ON l.v = a.src GROUP BY 1, 2"))(lambda s, d: (p := _pieces(s, d)) and scores.score_count(p["arcs"], p["labels"]))
query("score_weighted", _LOOP.sql("SELECT v, label, h AS score FROM h1"))(lambda s, d: (p := _pieces(s, d)) and scores.score_weighted(p["arcs"], p["labels"]))
query("score_balanced", _LOOP.sql("SELECT v, label, round(s, 9) AS score FROM s1"))(lambda s, d: _scored(_pieces(s, d)).select("v", "label", F.round("score", 9).alias("score")))
query("best_label", _LOOP.sql("SELECT v, best AS label FROM best1"))(lambda s, d: scores.best_label(_scored(_pieces(s, d), "compact"), SEED, 1, PORTABLE).select("v", F.col("best").alias("label")))
query("candidates", _LOOP.sql("SELECT v, cur, best FROM best1 WHERE best <> cur"))(lambda s, d: migrate.candidates(scores.best_label(_scored(_pieces(s, d), "compact"), SEED, 1, PORTABLE)).select("v", "cur", "best"))
query("loads_degree", _LOOP.sql("SELECT ids.label, CAST(coalesce(sum(deg), 0) AS BIGINT) AS b, count(verts.v) AS n FROM ids LEFT JOIN lab0 ON lab0.label = ids.label LEFT JOIN verts ON verts.v = lab0.v GROUP BY ids.label"))(lambda s, d: _pieces(s, d)["loads"])
query("loads_vertices", _LOOP.sql("SELECT label, count(*) AS b, count(*) AS n FROM lab0 GROUP BY label"))(lambda s, d: st.partition_loads(_pieces(s, d)["state"], "vertices"))
query("loads_weighted", _LOOP.sql("SELECT label, CAST(sum(wdeg) AS BIGINT) AS b, count(*) AS n FROM lab0 JOIN verts USING (v) GROUP BY label"))(lambda s, d: st.partition_loads(_pieces(s, d)["state"], "weighted_degree"))
query("capacity_penalty", _LOOP.sql("SELECT label, round(CAST(b AS DOUBLE) / c, 9) AS pi FROM loads1 CROSS JOIN cap"))(lambda s, d: (p := _pieces(s, d)) and st.penalty(p["loads"], p["cap"]).select("label", F.round("pi", 9).alias("pi")))
query("remaining_capacity", _LOOP.sql("SELECT label, round(c - CAST(b AS DOUBLE), 6) AS r FROM loads1 CROSS JOIN cap"))(lambda s, d: (p := _pieces(s, d)) and st.remaining(p["loads"], p["cap"]).select("label", F.round("r", 6).alias("r")))


def _cands(p: dict) -> DataFrame:
    return migrate.candidates(scores.best_label(_scored(p, "compact"), SEED, 1, PORTABLE))


query("candidate_load", _LOOP.sql("SELECT best AS label, CAST(sum(deg) AS BIGINT) AS m, count(*) AS n, min(deg) AS dmin, max(deg) AS dmax, CAST(sum(deg * deg) AS BIGINT) AS sum_deg2 FROM best1 WHERE best <> cur GROUP BY best"))(
    lambda s, d: migrate.candidate_loads(_cands(_pieces(s, d)))
)
query("migration_prob", _LOOP.sql("SELECT label, round(r, 6) AS r, m, round(p, 9) AS p FROM p1"))(
    lambda s, d: (p := _pieces(s, d)) and migrate.migration_probabilities(p["loads"], migrate.candidate_loads(_cands(p)), p["cap"]).select("label", F.round("r", 6).alias("r"), "m", F.round("p", 9).alias("p"))
)
query("migrate_once", _LOOP.labels_sql())(lambda s, d: blp(s, d, "g_events", 1).labels)
query("graph_score", _LOOP.sql("SELECT round(sum(s), 6) AS score FROM s1 WHERE label = cur"))(
    lambda s, d: (p := _pieces(s, d)) and scores.graph_score(scores.build_hist(p["arcs"], p["labels"]), p["state"], p["loads"], p["cap"]).select(F.round("score", 6).alias("score"))
)
query(
    "hist_delta",
    _LOOP.sql(
        "SELECT * FROM (SELECT v, label, CAST(sum(h) AS BIGINT) AS h, CAST(sum(n) AS BIGINT) AS n FROM (SELECT a.dst AS v, unnest([b.label, c.label]) AS label, unnest([-a.w, a.w]) AS h, unnest([-1, 1]) AS n FROM lab0 b JOIN lab1 c USING (v) JOIN arcs a ON a.src = b.v WHERE b.label <> c.label) GROUP BY v, label) WHERE h <> 0 OR n <> 0"
    ),
)(lambda s, d: (p := _pieces(s, d)) and scores.hist_delta(p["arcs"], p["labels"].withColumnRenamed("label", "old").join(blp(s, d, "g_events", 1).labels.withColumnRenamed("label", "new"), "v").where("old <> new")))
query(
    "overflow_bound",
    _LOOP.sql(
        """SELECT p.label, x.eps, round(CASE WHEN q.dmax = q.dmin THEN 0.0 ELSE exp(-2.0 * q.n * power(x.eps * p.r / nullif(q.dmax - q.dmin, 0), 2)) END, 6) AS bound
FROM p1 p JOIN (SELECT best AS label, count(*) AS n, min(deg) AS dmin, max(deg) AS dmax FROM best1 WHERE best <> cur GROUP BY best) q USING (label) CROSS JOIN (SELECT CAST(unnest([0.2, 0.4]) AS DOUBLE) AS eps) x"""
    ),
)(lambda s, d: (p := _pieces(s, d)) and _bounds(p, migrate.candidate_loads(_cands(p))))


def _bounds(p: dict, m: DataFrame) -> DataFrame:
    rows = migrate.migration_probabilities(p["loads"], m, p["cap"]).select("label", "r").join(m.select("label", "n", "dmin", "dmax"), "label")
    rows = rows.withColumn("eps", F.explode(F.array(F.lit(0.2), F.lit(0.4))))
    return rows.select("label", "eps", F.round(bounds.overflow_bound_column(*map(F.col, ("n", "r", "eps", "dmin", "dmax"))), 6).alias("bound"))


query("overflow_bound_sum", _LOOP.sql("SELECT p.label, round(exp(-2 * power(0.2 * r, 2) / q), 6) AS bound FROM p1 p JOIN (SELECT best AS label, sum(deg * deg) AS q FROM best1 WHERE best <> cur GROUP BY best) USING (label)"))(
    lambda s, d: (p := _pieces(s, d))
    and (m := migrate.candidate_loads(_cands(p)))
    and migrate.migration_probabilities(p["loads"], m, p["cap"]).join(m.select("label", "sum_deg2"), "label").select("label", F.round(bounds.overflow_bound_sum_column(F.col("sum_deg2"), F.col("r"), 0.2), 6).alias("bound"))
)

# -- the method, fixed numbers of iterations, exact


def blp(s: SparkSession, d: str, graph: str, t: int, k: int = K, **options) -> PartitionResult:
    return partition(_graph(graph)(s, d), k, directed=graph in graphs.DIRECTED, seed=SEED, provider=PORTABLE, halting=FixedIterations(t), **options)


for _t in (1, 3, 5):
    query(f"blp_t{_t}", Loop(_e("g_cust_supp"), K, _t, directed=False).labels_sql())(lambda s, d, t=_t: blp(s, d, "g_cust_supp", t).labels)
query("blp_t5_directed_events", Loop(_e("g_events"), K, 5).labels_sql())(lambda s, d: blp(s, d, "g_events", 5).labels)
query("blp_t3_web", Loop(_e("g_web"), K, 3).labels_sql())(lambda s, d: blp(s, d, "g_web", 3).labels)
query("blp_t3_rebuild", Loop(_e("g_events"), K, 3).labels_sql())(lambda s, d: blp(s, d, "g_events", 3, hist_mode="rebuild", candidate_set="all_k").labels)
query("blp_t3_unthrottled", Loop(_e("g_cust_supp"), K, 3, directed=False, throttle=False).labels_sql())(lambda s, d: blp(s, d, "g_cust_supp", 3, throttle="none").labels)
query("blp_t3_vertex_balance", Loop(_e("g_cust_supp"), K, 3, directed=False, unit="vertices").labels_sql())(lambda s, d: blp(s, d, "g_cust_supp", 3, unit="vertices").labels)
query("blp_history_t5", Loop(_e("g_cust_supp"), K, 5, directed=False).history_sql())(
    lambda s, d: blp(s, d, "g_cust_supp", 5).history_frame(s).select("t", F.round("phi", 6).alias("phi"), F.round("rho", 6).alias("rho"), "migrated", "messages")
)


@query("plain_lpa_t3")
def plain_lpa_t3(s: SparkSession, d: str) -> DataFrame:
    return baselines.plain_lpa(_graph("g_events")(s, d), K, seed=SEED, provider=PORTABLE, halting=FixedIterations(2))[0]


def _plain_sql(t: int) -> str:
    base = Loop(_e("g_events"), K, 0)
    ctes = list(base.ctes)
    for i in range(1, t + 1):
        ctes += [
            (f"h{i}", f"SELECT a.dst AS v, l.label, sum(a.w) AS h FROM arcs a JOIN lab{i - 1} l ON l.v = a.src GROUP BY a.dst, l.label"),
            (f"lab{i}", f"SELECT v, label FROM (SELECT h.v, h.label, row_number() OVER (PARTITION BY h.v ORDER BY h.h DESC, (h.label = c.label) DESC, {draw_sql(SEED, i, 'tie', 'h.v', 'h.label')} DESC, h.label DESC) AS r FROM h{i} h JOIN lab{i - 1} c ON c.v = h.v) WHERE r = 1"),
        ]
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({q})" for n, q in ctes) + f"\nSELECT v, label FROM lab{t}"


ORACLE["plain_lpa_t3"] = _plain_sql(3)

# -- the method to its halt, and its variants

for _name in ("g_cust_supp", "g_events", "g_web", "g_doc", "g_conv"):
    query(f"blp_full_{_name[2:]}")(lambda s, d, g=_name: partition(_graph(g)(s, d), K, directed=g in graphs.DIRECTED, max_iter=200 if g in TO_HALT else FULL).history_frame(s).select("t", "phi", "rho", "score", "migrated", "messages"))
query("blp_async_per_task")(lambda s, d: partition(_graph("g_web")(s, d), K, async_mode="per_task", max_iter=FULL // 2).history_frame(s).select("t", "phi", "rho", "migrated"))
query("blp_sequential")(lambda s, d: partition(_graph("g_web")(s, d), K, async_mode="sequential", max_iter=FULL // 2).history_frame(s).select("t", "phi", "rho", "migrated"))
query("blp_uneven_capacities")(lambda s, d: partition(_graph("g_web")(s, d), K, capacity_weights={i: 2.0 if i < 2 else 1.0 for i in range(K)}, max_iter=FULL // 2).history_frame(s).select("t", "phi", "rho", "migrated"))
query("blp_batched")(lambda s, d: partition(_graph("g_web")(s, d), K, async_mode="batched", max_iter=FULL // 2).history_frame(s).select("t", "phi", "rho", "migrated"))

# -- change

_CUT = "2001-06-15"
_OLD = f"SELECT src, dst FROM ({GRAPH_SQL['g_order_part']}) WHERE ts <= TIMESTAMP '{_CUT}'"
_HALF = f"SELECT src, dst FROM ({_e('g_events')}) WHERE (src + dst) % 20 <> 0"


def _half(s: SparkSession, d: str) -> DataFrame:
    return _graph("g_events")(s, d).where(F.pmod(F.col("src") + F.col("dst"), F.lit(20)) != 0)


query("snapshot_split", f"SELECT count(*) AS kept, (SELECT count(*) FROM ({_e('g_order_part')})) AS edges FROM ({_OLD})")(
    lambda s, d: adapt.snapshot(graphs.g_order_part(s, d), _CUT).agg(F.count(F.lit(1)).alias("kept")).crossJoin(_graph("g_order_part")(s, d).agg(F.count(F.lit(1)).alias("edges")))
)
query("diff_edges", f"SELECT 'add' AS op, src, dst FROM ({_e('g_events')}) WHERE (src + dst) % 20 = 0")(lambda s, d: adapt.diff_edges(_half(s, d), _graph("g_events")(s, d)))
query("apply_changes", _e("g_events"))(lambda s, d: adapt.apply_changes(_half(s, d), adapt.diff_edges(_half(s, d), _graph("g_events")(s, d))))
_OLD_LABELS = f"SELECT v, CAST({draw_sql(SEED, 0, 'init', 'v')} % {K} AS INTEGER) AS label FROM (SELECT src AS v FROM ({_HALF}) UNION SELECT dst FROM ({_HALF})) WHERE v % 3 <> 0"


def _old_labels(s: SparkSession, d: str) -> DataFrame:
    h = _half(s, d)
    v = h.select(F.col("src").alias("v")).union(h.select("dst")).distinct().where("v % 3 <> 0")
    return st.init_random(v, K, SEED, PORTABLE)


_LEAST = f"""SELECT x.v, CAST(coalesce(o.label, (SELECT label FROM (SELECT ids.label, coalesce(sum(CASE WHEN q.label IS NULL THEN 0 ELSE verts.deg END), 0) AS b FROM ids LEFT JOIN ({_OLD_LABELS}) q ON q.label = ids.label LEFT JOIN verts ON verts.v = q.v GROUP BY ids.label) ORDER BY b, label LIMIT 1)) AS INTEGER) AS label
FROM verts x LEFT JOIN ({_OLD_LABELS}) o ON o.v = x.v"""
_NEW_LOOP = Loop(_e("g_events"), K, 3, start=_LEAST)
query("new_vertices_least_loaded", _NEW_LOOP.sql("SELECT v, label FROM lab0"))(lambda s, d: st.init_from(_old_labels(s, d), convert.vertex_stats(convert.to_weighted_undirected(_graph("g_events")(s, d))), "least_loaded", K))
query(
    "new_vertices_random", Loop(_e("g_events"), K, 0).sql(f"SELECT x.v, CAST(coalesce(o.label, {draw_sql(SEED, 0, 'new', 'x.v')} % {K}) AS INTEGER) AS label FROM verts x LEFT JOIN ({_OLD_LABELS}) o ON o.v = x.v")
)(lambda s, d: st.init_from(_old_labels(s, d), convert.vertex_stats(convert.to_weighted_undirected(_graph("g_events")(s, d))), "random", K, SEED, PORTABLE))
query("new_vertices_water_fill")(lambda s, d: st.init_from(_old_labels(s, d), convert.vertex_stats(convert.to_weighted_undirected(_graph("g_events")(s, d))), "water_fill", K))
query("adapt_t3_all", _NEW_LOOP.labels_sql())(lambda s, d: adapt.adapt_graph(_old_labels(s, d), _graph("g_events")(s, d), K, seed=SEED, provider=PORTABLE, halting=FixedIterations(3)).labels)
_ENDS = f"SELECT src AS v FROM ({_e('g_events')}) WHERE (src + dst) % 20 = 0 UNION SELECT dst FROM ({_e('g_events')}) WHERE (src + dst) % 20 = 0"
query("adapt_t3_affected", Loop(_e("g_events"), K, 3, start=_LEAST, active=_ENDS).labels_sql())(
    lambda s, d: adapt.adapt_graph(_old_labels(s, d), _graph("g_events")(s, d), K, scope="affected", edges_old=_half(s, d), seed=SEED, provider=PORTABLE, halting=FixedIterations(3)).labels
)
query("stream_assign", _NEW_LOOP.sql("SELECT v, label FROM lab0"))(lambda s, d: adaptive.stream_assign(convert.vertex_stats(convert.to_weighted_undirected(_graph("g_events")(s, d))), _old_labels(s, d), K))


def _sent_sql(loop: Loop) -> str:
    return f"SELECT sum(messages) AS messages FROM ({loop.history_sql()})"


def _saved(s: SparkSession, d: str) -> DataFrame:
    after = adapt.adapt_graph(_old_labels(s, d), _graph("g_events")(s, d), K, seed=SEED, provider=PORTABLE, halting=FixedIterations(3))
    scratch = blp(s, d, "g_events", 3)
    return s.createDataFrame([(after.messages, scratch.messages, round(metrics.savings(after, scratch)["messages"], 6))], "adapted long, scratch long, saved double")


query("messages", f"SELECT CAST(messages AS BIGINT) AS messages FROM ({_sent_sql(Loop(_e('g_events'), K, 3))})")(lambda s, d: s.createDataFrame([(blp(s, d, "g_events", 3).messages,)], "messages long"))
query("savings", f"SELECT CAST(a.messages AS BIGINT) AS adapted, CAST(b.messages AS BIGINT) AS scratch, round(1 - CAST(a.messages AS DOUBLE) / b.messages, 6) AS saved FROM ({_sent_sql(_NEW_LOOP)}) a CROSS JOIN ({_sent_sql(Loop(_e('g_events'), K, 3))}) b")(_saved)


@query("stream_adapt")
def stream_adapt(s: SparkSession, d: str) -> DataFrame:
    """(batch, t, phi, rho): a labelling of the web graph's older edges, adapted to a stream of the others."""
    at = f"{shared_folder(s)}/stream-{uuid.uuid4().hex}"
    e = durable(_graph("g_web")(s, d))
    fresh = F.pmod(F.col("src") + F.col("dst"), F.lit(20)) == 0
    old = e.where(~fresh)
    e.where(fresh).write.parquet(f"{at}/in")
    adaptive.start_state(partition(old, K, max_iter=3).labels, old, f"{at}/state", K)
    stream = s.readStream.schema("src long, dst long").parquet(f"{at}/in")
    adaptive.stream_adapt(stream, f"{at}/state", K, f"{at}/check", iterations=2).trigger(availableNow=True).start().awaitTermination()
    _, m = adaptive.load_state(s, f"{at}/state/1")
    return s.createDataFrame([(1, m["t"], m["phi"], m["rho"])], "batch long, t int, phi double, rho double")


query("adapt_affected")(lambda s, d: adapt.adapt_graph(_old_labels(s, d), _graph("g_events")(s, d), K, scope="affected", edges_old=_half(s, d), max_iter=4).history_frame(s).select("t", "phi", "rho", "migrated", "messages"))

_GROW = f"CASE WHEN {draw_sql(SEED, 0, 'grow', 'v')} / 4294967296.0 < {2 / (K + 2)!r} THEN {K} + {draw_sql(SEED, 0, 'pick', 'v')} % 2 ELSE label END"
_SHRINK = f"CASE WHEN label IN (1, 5) THEN [0, 2, 3, 4, 6, 7][{draw_sql(SEED, 0, 'shrink', 'v')} % 6 + 1] ELSE label END"
_BASE_LABELS = f"SELECT v, CAST({draw_sql(SEED, 0, 'init', 'v')} % {K} AS INTEGER) AS label FROM verts"
query("elastic_add_seed", Loop(_e("g_events"), K, 0).sql(f"SELECT v, CAST({_GROW} AS INTEGER) AS label FROM lab0"))(lambda s, d: adapt.reseed_k(_pieces(s, d)["labels"], list(range(K)), add=2, seed=SEED, provider=PORTABLE)[0])
query("elastic_remove_seed", Loop(_e("g_events"), K, 0).sql(f"SELECT v, CAST({_SHRINK} AS INTEGER) AS label FROM lab0"))(lambda s, d: adapt.reseed_k(_pieces(s, d)["labels"], list(range(K)), remove=[1, 5], seed=SEED, provider=PORTABLE)[0])
query("elastic_add_t3", Loop(_e("g_events"), K + 2, 3, start=f"SELECT v, CAST({_GROW} AS INTEGER) AS label FROM ({_BASE_LABELS})").labels_sql())(
    lambda s, d: adapt.adapt_k(_pieces(s, d)["labels"], _graph("g_events")(s, d), list(range(K)), add=2, seed=SEED, provider=PORTABLE, halting=FixedIterations(3)).labels
)
query("elastic_remove_t3", Loop(_e("g_events"), K - 2, 3, start=f"SELECT v, CAST({_SHRINK} AS INTEGER) AS label FROM ({_BASE_LABELS})", labels=[0, 2, 3, 4, 6, 7]).labels_sql())(
    lambda s, d: adapt.adapt_k(_pieces(s, d)["labels"], _graph("g_events")(s, d), list(range(K)), remove=[1, 5], seed=SEED, provider=PORTABLE, halting=FixedIterations(3)).labels
)

# -- baselines

_VERTS = Loop(_e("g_events"), K, 0)
query("hash_partition", _VERTS.sql(f"SELECT v, CAST(v % {K} AS INTEGER) AS label FROM verts"))(lambda s, d: baselines.hash_partition(_pieces(s, d)["verts"], K))
query("chunk_partition", _VERTS.sql(f"SELECT v, CAST((row_number() OVER (ORDER BY v) - 1) // ((SELECT count(*) FROM verts) + {K - 1}) // 1 AS INTEGER) AS label FROM verts").replace(f"((SELECT count(*) FROM verts) + {K - 1}) // 1", f"(((SELECT count(*) FROM verts) + {K - 1}) // {K})"))(
    lambda s, d: baselines.chunk_partition(_pieces(s, d)["verts"], K)
)


def _quality_sql(label: str) -> str:
    return _VERTS.sql(
        f"""SELECT round(avg(CASE WHEN x.label = y.label THEN 1.0 ELSE 0.0 END), 6) AS phi,
(SELECT round(max(b) * {K}.0 / sum(b), 6) FROM (SELECT sum(deg) AS b FROM (SELECT v, {label} AS label, deg FROM verts) GROUP BY label)) AS rho
FROM arcs a JOIN (SELECT v, {label} AS label FROM verts) x ON x.v = a.src JOIN (SELECT v, {label} AS label FROM verts) y ON y.v = a.dst"""
    )


def _quality(s: SparkSession, d: str, make) -> DataFrame:
    p = _pieces(s, d)
    labels = make(p["verts"])
    return metrics.phi(p["arcs"], labels).crossJoin(metrics.rho(p["verts"].join(labels, "v"), K))


query("hash_quality", _quality_sql(f"v % {K}"))(lambda s, d: _quality(s, d, lambda v: baselines.hash_partition(v, K)))
query("random_quality", _quality_sql(f"{draw_sql(SEED, 0, 'init', 'v')} % {K}"))(lambda s, d: _quality(s, d, lambda v: baselines.random_partition(v, K, SEED, PORTABLE)))


def _judged(make, graph: str = "g_web", k: int = K) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        e = _graph(graph)(s, d)
        return metrics.quality(e, make(e, k), k, graph in graphs.DIRECTED)

    return run


query("stream_greedy")(_judged(lambda e, k: baselines.stream_greedy(e, k)))
query("stream_greedy_batches")(_judged(lambda e, k: baselines.stream_greedy(e, k, batches=8)))
query("stream_greedy_bfs_exponential")(_judged(lambda e, k: baselines.stream_greedy(e, k, order="bfs", weight="exponential")))
query("stream_interpolated")(_judged(lambda e, k: baselines.stream_interpolated(e, k)))
query("multilevel")(_judged(lambda e, k: baselines.multilevel_partition(e, k, coarse_target=300)))
query("coarsen_lpa")(_judged(lambda e, k: baselines.coarsen_lpa_partition(e, k, coarse_target=300)))
query("central_lpa")(_judged(lambda e, k: baselines.central_lpa(e, k, iterations=6)))

# -- measures, on labels after 3 iterations of g_events

_L3 = Loop(_e("g_events"), K, 3)
_MARKED = "SELECT a.src, a.dst, x.label AS src_label, y.label AS dst_label FROM e a JOIN lab3 x ON x.v = a.src JOIN lab3 y ON y.v = a.dst"


def _l3(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return _graph("g_events")(s, d), blp(s, d, "g_events", 3).labels


query("phi", _L3.sql(f"SELECT round(avg(CASE WHEN src_label = dst_label THEN 1.0 ELSE 0.0 END), 6) AS phi FROM ({_MARKED})"))(lambda s, d: metrics.phi(*_l3(s, d)))
query("phi_weighted", _L3.sql(f"SELECT round(avg(CASE WHEN src_label = dst_label THEN 1.0 ELSE 0.0 END), 6) AS phi FROM ({_MARKED})"))(
    lambda s, d: (x := _l3(s, d)) and metrics.phi_weighted(convert.to_weighted_undirected(x[0]), x[1])
)
query("rho", _L3.sql(f"SELECT round(max(b) * {K}.0 / sum(b), 6) AS rho FROM (SELECT sum(deg) AS b FROM lab3 JOIN verts USING (v) GROUP BY label)"))(
    lambda s, d: (x := _l3(s, d)) and metrics.rho(convert.vertex_stats(convert.to_weighted_undirected(x[0])).join(x[1], "v"), K)
)
query("rho_vertices", _L3.sql(f"SELECT round(max(b) * {K}.0 / sum(b), 6) AS rho FROM (SELECT count(*) AS b FROM lab3 GROUP BY label)"))(
    lambda s, d: (x := _l3(s, d)) and metrics.rho(convert.vertex_stats(convert.to_weighted_undirected(x[0])).join(x[1], "v"), K, "vertices")
)
query("cut_edges", _L3.sql(f"SELECT count(*) FILTER (WHERE src_label <> dst_label) AS cut, count(*) AS edges FROM ({_MARKED})"))(lambda s, d: metrics.cut_edges(*_l3(s, d)))
query("cut_matrix_rollup", _L3.sql(f"SELECT src_label, dst_label, count(*) AS n FROM ({_MARKED}) GROUP BY ROLLUP (src_label, dst_label)"))(lambda s, d: metrics.cut_matrix(*_l3(s, d)))
query("boundary_vertices", _L3.sql("SELECT a.src AS v, count(*) AS remote_degree FROM arcs a JOIN lab3 x ON x.v = a.src JOIN lab3 y ON y.v = a.dst WHERE x.label <> y.label GROUP BY a.src"))(lambda s, d: metrics.boundary_vertices(*_l3(s, d)))
query("induced_subgraph", _L3.sql(f"SELECT src, dst FROM ({_MARKED}) WHERE src_label = 0 AND dst_label = 0"))(lambda s, d: metrics.induced(*_l3(s, d), 0))
query("partition_difference", _L3.sql("SELECT round(avg(CASE WHEN a.label <> b.label THEN 1.0 ELSE 0.0 END), 6) AS difference, count(*) AS vertices FROM lab0 a JOIN lab3 b USING (v)"))(
    lambda s, d: metrics.partition_difference(_pieces(s, d)["labels"], _l3(s, d)[1])
)
query("compare_confusion", _L3.sql("SELECT a.label AS la, b.label AS lb, count(*) AS n FROM lab0 a JOIN lab3 b USING (v) GROUP BY 1, 2"))(lambda s, d: metrics.confusion(_pieces(s, d)["labels"], _l3(s, d)[1]))
query(
    "locality_gain",
    _L3.sql(
        f"SELECT phi, phi_base, round(phi / phi_base, 6) AS gain FROM (SELECT round(avg(CASE WHEN src_label = dst_label THEN 1.0 ELSE 0.0 END), 6) AS phi, round(avg(CASE WHEN src % {K} = dst % {K} THEN 1.0 ELSE 0.0 END), 6) AS phi_base FROM ({_MARKED}))"
    ),
)(lambda s, d: (x := _l3(s, d)) and metrics.locality_gain(*x, baselines.hash_partition(_pieces(s, d)["verts"], K)))
query("quality_row", _L3.sql(f"""SELECT (SELECT round(avg(CASE WHEN x.label = y.label THEN 1.0 ELSE 0.0 END), 6) FROM arcs a JOIN lab3 x ON x.v = a.src JOIN lab3 y ON y.v = a.dst) AS phi,
(SELECT round(avg(CASE WHEN src_label = dst_label THEN 1.0 ELSE 0.0 END), 6) FROM ({_MARKED})) AS phi_w,
(SELECT CAST(count(*) / 2 AS BIGINT) FROM arcs a JOIN lab3 x ON x.v = a.src JOIN lab3 y ON y.v = a.dst WHERE x.label <> y.label) AS cut,
(SELECT round(max(b) * {K}.0 / sum(b), 6) FROM (SELECT sum(deg) AS b FROM lab3 JOIN verts USING (v) GROUP BY label)) AS rho,
(SELECT round(max(b) * {K}.0 / sum(b), 6) FROM (SELECT count(*) AS b FROM lab3 GROUP BY label)) AS rho_v"""))(lambda s, d: metrics.quality(*_l3(s, d), K))
query("idle_fraction", _L3.sql(f"SELECT round(1 - avg(w) / max(w), 6) AS idle FROM (SELECT label, sum(x) AS w FROM (SELECT src_label AS label, count(*) AS x FROM ({_MARKED}) GROUP BY 1 UNION ALL SELECT dst_label, count(*) FROM ({_MARKED}) GROUP BY 1) GROUP BY label)"))(
    lambda s, d: metrics.idle_fraction(apps.worker_load(*_l3(s, d))).select("idle")
)
query("app_messages", _L3.sql(f"SELECT count(*) AS messages, count(*) FILTER (WHERE src_label <> dst_label) AS remote FROM ({_MARKED})"))(lambda s, d: apps.app_messages(*_l3(s, d)))
_HASHED = f"SELECT count(*) AS messages, count(*) FILTER (WHERE src % {K} <> dst % {K}) AS remote FROM e"
query("app_messages_hash_vs_blp", _L3.sql(f"SELECT 'hash' AS approach, messages, remote FROM ({_HASHED}) UNION ALL SELECT 'method', count(*), count(*) FILTER (WHERE src_label <> dst_label) FROM ({_MARKED})"))(
    lambda s, d: (x := _l3(s, d))
    and apps.app_messages(x[0], baselines.hash_partition(x[1], K)).select(F.lit("hash").alias("approach"), "messages", "remote").union(apps.app_messages(*x).select(F.lit("method"), "messages", "remote"))
)
_WEB3 = Loop(_e("g_web"), K, 3)
query(
    "quality_cube",
    _WEB3.sql(
        """SELECT v % 8 AS kind, label, count(*) AS vertices, CAST(sum(deg) AS BIGINT) AS load, CAST(sum(remote) AS BIGINT) AS remote FROM lab3 JOIN verts USING (v)
JOIN (SELECT a.src AS v, count(*) FILTER (WHERE x.label <> y.label) AS remote FROM arcs a JOIN lab3 x ON x.v = a.src JOIN lab3 y ON y.v = a.dst GROUP BY a.src) USING (v) GROUP BY CUBE (v % 8, label)"""
    ),
)(lambda s, d: (r := blp(s, d, "g_web", 3)) and metrics.quality_cube(_graph("g_web")(s, d), r.labels, r.vertices))
_E6 = Loop(_e("g_events"), K, 6)
_TRACE = " UNION ALL ".join(f"SELECT {t} AS t, sum(s) / count(*) AS x FROM s{t + 1} WHERE label = cur" for t in range(6))
query(
    "patience_window",
    _E6.sql(f"SELECT t, round(x, 6) AS score, coalesce(count(g) OVER w = 2 AND max(g) OVER w <= 0.05, FALSE) AS stagnant FROM (SELECT t, x, x - lag(x) OVER (ORDER BY t) AS g FROM ({_TRACE})) WINDOW w AS (ORDER BY t ROWS BETWEEN 1 PRECEDING AND CURRENT ROW)"),
)(lambda s, d: (r := blp(s, d, "g_events", 5)) and metrics.patience_window(r.history_frame(s), r.vertices.count(), 0.05, 2))
query(
    "flow_matrix",
    _LOOP.sql(
        """SELECT CAST(1 AS INTEGER) AS t, f.from_label, f.to_label, round(CAST(f.x AS DOUBLE) / b.b, 6) AS x
FROM (SELECT a.label AS from_label, c.label AS to_label, sum(deg) AS x FROM lab0 a JOIN lab1 c USING (v) JOIN verts USING (v) WHERE a.label <> c.label GROUP BY 1, 2) f JOIN (SELECT label, sum(deg) AS b FROM lab0 JOIN verts USING (v) GROUP BY label) b ON b.label = f.from_label
UNION ALL SELECT 1, a.label, a.label, round(CAST(sum(CASE WHEN a.label = c.label THEN deg ELSE 0 END) AS DOUBLE) / sum(deg), 6) FROM lab0 a JOIN lab1 c USING (v) JOIN verts USING (v) GROUP BY a.label"""
    ),
)(
    lambda s, d: (r := blp(s, d, "g_events", 3, record_flows=True)) and bounds.flow_matrix(r.flows_frame(s).where("t = 1"), st.partition_loads(_pieces(s, d)["state"]).withColumn("t", F.lit(1)))
)



def _loads_sql(t: int) -> str:
    return f"SELECT ids.label, CAST(coalesce(sum(deg), 0) AS BIGINT) AS b FROM ids LEFT JOIN lab{t} l ON l.label = ids.label LEFT JOIN verts USING (v) GROUP BY ids.label"


def _distance_sql(t: int) -> str:
    return f"SELECT {t} AS t, max(abs(b - total / {K}.0)) / (SELECT max(b) FROM ({_loads_sql(0)})) AS d FROM ({_loads_sql(t)}) CROSS JOIN cap"


_DISTANCES = " UNION ALL ".join(_distance_sql(t) for t in range(4))


def _distances(s: SparkSession, d: str) -> list[float]:
    return bounds.load_distance([list(map(float, x.values())) for x in blp(s, d, "g_events", 3).loads])


query("load_history", _L3.sql(" UNION ALL ".join(f"SELECT {t} AS t, label, b FROM ({_loads_sql(t)})" for t in range(4))))(lambda s, d: blp(s, d, "g_events", 3).loads_frame(s))
query("load_distance", _L3.sql(f"SELECT t, round(d, 6) AS distance FROM ({_DISTANCES})"))(lambda s, d: s.createDataFrame([(t, round(x, 6)) for t, x in enumerate(_distances(s, d))], "t int, distance double"))
query("load_decay", _L3.sql(f"SELECT round(exp(regr_slope(ln(d), t)), 6) AS mu FROM ({_DISTANCES}) WHERE d > 0"))(lambda s, d: s.createDataFrame([(round(bounds.decay_fit(_distances(s, d)), 6),)], "mu double"))
query("flow_connectivity")(
    lambda s, d: (r := blp(s, d, "g_events", 3, record_flows=True)) and s.createDataFrame([(b, bounds.is_b_connected(r.flows, r.label_set, b)) for b in (1, 2, 3)], "span int, connected boolean")
)
query(
    "overflow_frequency",
    _L3.sql(
        " UNION ALL ".join(
            f"""SELECT {t} AS t, p.label, round(p.r, 6) AS r, l.b, l.b > cap.c AS over, l.b > cap.c + 0.2 * p.r AS beyond, round(exp(-2 * power(0.2 * p.r, 2) / q.q), 6) AS bound
FROM p{t} p JOIN ({_loads_sql(t)}) l USING (label) JOIN (SELECT best AS label, sum(deg * deg) AS q FROM best{t} WHERE best <> cur GROUP BY best) q USING (label) CROSS JOIN cap"""
            for t in (1, 2, 3)
        )
    ),
)(lambda s, d: bounds.overflow_frequency(s, blp(s, d, "g_events", 3, record_flows=True), 0.2))
query("within_slack", _L3.sql(f"SELECT round((max(b) * {K}.0 / sum(b) - 1) * 100, 4) AS unbalance_percent, max(b) * {K}.0 / sum(b) <= 1.05 AS within FROM ({_loads_sql(3)})"))(
    lambda s, d: (x := metrics.within_slack(blp(s, d, "g_events", 3).history[-1]["rho"], 1.05)) and s.createDataFrame([(round(x["unbalance_percent"], 4), x["within"])], "unbalance_percent double, within boolean")
)

# -- applications

_PR = Loop(_e("g_events"), K, 0)


def _pagerank_sql(iters: int) -> str:
    ctes = [*_PR.ctes[:1], ("vs", "SELECT src AS v FROM e UNION SELECT dst FROM e"), ("base", "SELECT vs.v, o.out FROM vs LEFT JOIN (SELECT src, count(*) AS out FROM e GROUP BY src) o ON o.src = vs.v"), ("n", "SELECT count(*) AS n FROM base"), ("r0", "SELECT v, out, 1.0::DOUBLE / n AS rank FROM base CROSS JOIN n")]
    for i in range(1, iters + 1):
        p = f"r{i - 1}"
        ctes.append((f"r{i}", f"SELECT b.v, b.out, 0.15::DOUBLE / n.n + 0.85::DOUBLE * (coalesce(m.m, 0) + coalesce((SELECT sum(rank) FROM {p} WHERE out IS NULL), 0) / n.n) AS rank FROM base b CROSS JOIN n LEFT JOIN (SELECT e.dst, sum(r.rank / r.out) AS m FROM e JOIN {p} r ON r.v = e.src GROUP BY e.dst) m ON m.dst = b.v"))
    return "WITH " + ",\n".join(f"{a} AS MATERIALIZED ({b})" for a, b in ctes) + f"\nSELECT v, round(rank, 9) AS rank FROM r{iters}"


query("pagerank_20", _pagerank_sql(20))(lambda s, d: apps.pagerank(_graph("g_events")(s, d)).select("v", F.round("rank", 9).alias("rank")))
query("sssp_bfs", f"WITH RECURSIVE e AS ({_e('g_web')}), a AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e), r(v, dist) AS (SELECT min(src), 0 FROM a UNION SELECT a.dst, r.dist + 1 FROM r JOIN a ON a.src = r.v WHERE r.dist < 30) SELECT v, CAST(min(dist) AS BIGINT) AS dist FROM r GROUP BY v")(
    lambda s, d: (a := convert.to_undirected(_graph("g_web")(s, d)).select("src", "dst")) and apps.sssp(a, a.agg(F.min("src")).first()[0])
)
query("wcc", f"WITH RECURSIVE e AS ({_e('g_conv')}), a AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e), r(v, c) AS (SELECT src, src FROM a UNION SELECT a.dst, r.c FROM r JOIN a ON a.src = r.v) SELECT v, min(c) AS component FROM r GROUP BY v")(
    lambda s, d: apps.wcc(_graph("g_conv")(s, d))
)
query("placed_layout", _L3.sql("SELECT x.label, 1::BIGINT AS parts, count(*) AS rows FROM e JOIN lab3 x ON x.v = e.src GROUP BY x.label"))(
    lambda s, d: (x := _l3(s, d)) and placement.parts_of_labels(placement.place(x[0].withColumnRenamed("src", "v"), x[1], K))
)

# -- around the method

query("edges_union_intersect_except", f"WITH a AS ({_e('g_events')}), b AS (SELECT dst AS src, src AS dst FROM a) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)")(
    lambda s, d: _set_ops(_graph("g_events")(s, d))
)


def _set_ops(a: DataFrame) -> DataFrame:
    b = a.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    n = lambda op, x: x.agg(F.count(F.lit(1)).alias("n")).select(F.lit(op).alias("op"), "n")
    return n("union", a.union(b).distinct()).union(n("intersect", a.intersect(b))).union(n("except", a.subtract(b)))


query("event_windows_tumbling", "SELECT time_bucket(INTERVAL 1 day, ts) AS start, count(*) AS n FROM events GROUP BY 1")(
    lambda s, d: load(s, d, "events").groupBy(F.date_trunc("day", "ts").alias("start")).agg(F.count(F.lit(1)).alias("n")).select(F.col("start").cast("timestamp_ntz").alias("start"), "n")
)
query("event_windows_sliding", "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 day, ts) AS start FROM events UNION ALL SELECT time_bucket(INTERVAL 1 day, ts) - INTERVAL 1 day FROM events) GROUP BY start")(
    lambda s, d: load(s, d, "events").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
)
query("href_extract", """SELECT page_id, href, count(*) AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages) GROUP BY page_id, href""")(
    lambda s, d: load(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).alias("href")).groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("n"))
)
query("event_sessions", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events) WHERE p IS NULL OR ts - p > INTERVAL 1 hour GROUP BY user_id")(
    lambda s, d: load(s, d, "events").withColumn("p", F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where(F.col("p").isNull() | (F.col("ts") - F.col("p") > F.expr("INTERVAL 1 HOUR"))).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))
)
query("props_json", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS bucket, count(*) AS n FROM events GROUP BY 1")(
    lambda s, d: load(s, d, "events").groupBy((F.get_json_object("props", "$.k").cast("long") % 10).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
)
query("asof_label", "SELECT e.event_id, (SELECT max_by(p.event_type, p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_id < e.event_id AND p.event_type IN ('signup', 'purchase')) AS last FROM events e WHERE e.event_type = 'error'")(
    lambda s, d: load(s, d, "events")
    .withColumn("last", F.last(F.when(F.col("event_type").isin("signup", "purchase"), F.col("event_type")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)))
    .where("event_type = 'error'")
    .select("event_id", "last")
)
query("coactivity_range_join", "SELECT a.user_id AS src, b.user_id AS dst, count(*) AS n FROM events a JOIN events b ON a.event_type = 'purchase' AND b.event_type = 'purchase' AND a.user_id < b.user_id AND b.ts BETWEEN a.ts - INTERVAL 10 minute AND a.ts + INTERVAL 10 minute GROUP BY 1, 2")(
    lambda s, d: _coactivity(load(s, d, "events"))
)


def _coactivity(events: DataFrame, seconds: int = 600) -> DataFrame:
    """Pairs of users with purchases within a span: a range join by buckets of the span, each row in three."""
    p = events.where("event_type = 'purchase'").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    cell = F.floor(F.col("us") / F.lit(seconds * 1_000_000))
    a = p.select(F.col("user_id").alias("src"), F.col("us").alias("a"), F.explode(F.array(cell - 1, cell, cell + 1)).alias("cell"))
    b = p.select(F.col("user_id").alias("dst"), F.col("us").alias("b"), cell.alias("cell"))
    return a.join(b, "cell").where((F.col("src") < F.col("dst")) & (F.abs(F.col("a") - F.col("b")) <= seconds * 1_000_000)).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


def flagship(s: SparkSession, d: str) -> DataFrame:
    """History of the method on the directed event graph."""
    return blp(s, d, "g_events", 3).history_frame(s).select("t", "phi", "rho", "score", "candidates", "migrated", "messages")


query("blp_flagship")(flagship)

for _name, _run in experiments.WORKLOADS.items():
    query(_name)(_run)
