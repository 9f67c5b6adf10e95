"""Exact fixtures and invariants of the partitioning engine."""

import collections
import math
import os

import pytest
from pyspark.sql import functions as F

from graphpart.operators import adapt, apps, baselines, bounds, convert, engine, metrics, migrate, scores
from graphpart.operators import state as st
from graphpart.operators.engine import FixedIterations, SteadyState, partition
from graphpart.session import durable, durable_as_dealt, release
from graphpart.sources import graphs

F1 = [(1, 2), (2, 1), (1, 3), (2, 3)]
PAIRS = [(1, 2, 2), (1, 3, 1), (2, 3, 1), (4, 5, 2), (4, 6, 1), (5, 6, 1), (3, 4, 1)]
LABELS = {1: 0, 2: 0, 3: 1, 4: 1, 5: 1, 6: 0}


def edges(spark, rows):
    return spark.createDataFrame(rows, "src long, dst long")


def f2(spark):
    arcs = spark.createDataFrame([(a, b, w) for u, v, w in PAIRS for a, b in ((u, v), (v, u))], "src long, dst long, w int")
    labels = spark.createDataFrame(list(LABELS.items()), "v long, label int")
    state = convert.vertex_stats(arcs).join(labels, "v")
    return arcs, labels, state


def test_reciprocal_pairs_weigh_two(spark):
    w = {(r.src, r.dst): r.w for r in convert.to_weighted_undirected(edges(spark, [*F1, (3, 3), (1, 3), (None, 2)])).collect()}
    assert w == {(1, 2): 2, (2, 1): 2, (1, 3): 1, (3, 1): 1, (2, 3): 1, (3, 2): 1}
    naive = {r.w for r in convert.to_undirected(edges(spark, F1)).collect()}
    assert naive == {1}
    arcs, cost = convert.convert_with_cost(edges(spark, F1))
    assert {(r.src, r.dst): r.w for r in arcs.collect()} == w
    assert tuple(cost.first()) == (4, 2, 2)


def test_one_iteration_fixture(spark):
    arcs, labels, state = f2(spark)
    loads = st.partition_loads(state, label_set=[0, 1])
    assert {r.label: r.b for r in loads.collect()} == {0: 6, 1: 8}
    cap = st.capacity(14, 2)
    assert cap == pytest.approx(7.35)
    hist = scores.build_hist(arcs, labels)
    want = {(1, 0): -22 / 147, (1, 1): -37 / 49, (4, 0): -111 / 196, (4, 1): -199 / 588, (6, 0): -40 / 49, (6, 1): -13 / 147}
    for kind in ("compact", "all_k"):
        s = scores.score_balanced(hist, state, loads, cap, kind)
        got = {(r.v, r.label): r.score for r in s.collect()}
        for key, x in want.items():
            if key in got:
                assert got[key] == pytest.approx(x)
        best = scores.best_label(s, 42, 1)
        cands = {r.v: r.best for r in migrate.candidates(best).collect()}
        assert cands == {3: 0, 6: 1}
    m = {r.label: r.m for r in migrate.candidate_loads(migrate.candidates(best)).collect()}
    assert m == {0: 3, 1: 2}
    assert migrate.migration_probability(cap - 6, 3) == pytest.approx(0.45)
    assert migrate.migration_probability(cap - 8, 2) == 0
    score = scores.graph_score(hist, state, loads, cap).first()[0]
    assert score == pytest.approx(-221 / 84)
    assert metrics.phi(arcs, labels).first()[0] == pytest.approx(3 / 7, abs=1e-6)
    assert metrics.phi_weighted(arcs, labels).first()[0] == pytest.approx(5 / 9, abs=1e-6)
    assert metrics.rho(state, 2).first()[0] == pytest.approx(8 / 7, abs=1e-6)


def test_delta_equals_rebuild(spark):
    arcs, labels, _ = f2(spark)
    moves = spark.createDataFrame([(3, 1, 0)], "v long, old int, new int")
    after = labels.withColumn("label", F.when(F.col("v") == 3, 0).otherwise(F.col("label")))
    row = lambda df: sorted(tuple(r) for r in df.select("v", "label", "h", "n").collect())
    assert row(scores.apply_delta(scores.build_hist(arcs, labels), scores.hist_delta(arcs, moves))) == row(scores.build_hist(arcs, after))


def test_halting_counts_stagnant_iterations():
    halt = SteadyState(0.001, 5)
    trace = [0, 0.1, 0.2, 0.2005, 0.2009, 0.2010, 0.2010, 0.2010, 0.2010]
    assert [halt(x, 1, None) for x in trace] == [False] * 8 + [True]
    fixed = FixedIterations(20, record_halt=True)
    for x in [*trace, 0.3]:
        fixed(x, 1, None)
    assert fixed.halted_at == 8


def test_planted_blocks_are_found_and_balanced(spark):
    e = graphs.planted(spark, 4, 40, 8, 1)
    r = partition(e, 4, max_iter=14, seed=1)
    labels = r.labels
    assert r.history[-1]["phi"] > 0.5 > r.history[0]["phi"]
    assert r.history[-1]["rho"] < 1.25
    assert labels.count() == 160
    loads = st.partition_loads(labels.join(r.vertices, "v"))
    assert loads.agg(F.sum("b")).first()[0] == r.vertices.agg(F.sum("deg")).first()[0]


def test_layout_does_not_change_labels(spark):
    e = graphs.small_world(spark, 60, 3, 0.3)
    one = partition(e, 3, halting=FixedIterations(2)).labels
    other = partition(e.repartition(7).orderBy("dst"), 3, halting=FixedIterations(2), hist_mode="rebuild", candidate_set="all_k").labels
    assert metrics.partition_difference(one, other).first()["difference"] == 0


@pytest.mark.parametrize("rows", [[], [(1, 1)], [(1, 2), (1, 2), (2, 1)]])
def test_degenerate_graphs(spark, rows):
    r = partition(edges(spark, rows), 2, max_iter=2)
    assert r.labels.count() == (2 if rows and rows[0] != (1, 1) else 0)


def test_hub_over_capacity_warns(spark):
    with pytest.warns(UserWarning, match="exceeds the capacity"):
        partition(edges(spark, [(0, i) for i in range(1, 101)]), 4, max_iter=1)


def test_overflow_bound_example():
    b2, b4 = bounds.overflow_bound(200, 158.3, 0.2, 1, 500), bounds.overflow_bound(200, 158.3, 0.4, 1, 500)
    assert b2 < 0.2 and b4 < 0.0016
    assert b4 == pytest.approx(b2**4)


def test_elastic_shares(spark):
    v = spark.range(20000).select(F.col("id").alias("v"))
    labels = st.init_random(v, 4)
    grown, ids = adapt.reseed_k(labels, [0, 1, 2, 3], add=1)
    assert ids == [0, 1, 2, 3, 4]
    assert metrics.partition_difference(labels, grown).first()["difference"] == pytest.approx(0.2, abs=0.02)
    less, ids = adapt.reseed_k(labels, [0, 1, 2, 3], remove=[3])
    assert ids == [0, 1, 2]
    moved = labels.withColumnRenamed("label", "a").join(less, "v").where("a <> label").select("a").distinct().collect()
    assert [r.a for r in moved] == [3]


def test_differences_and_changes(spark):
    a = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (4, 1)], "v long, label int")
    b = spark.createDataFrame([(1, 0), (2, 1), (3, 1), (4, 0), (9, 0)], "v long, label int")
    assert metrics.partition_difference(a, b).first()["difference"] == 0.5
    old, new = edges(spark, [(1, 2), (2, 3)]), edges(spark, [(2, 3), (3, 4)])
    assert adapt.apply_changes(old, adapt.diff_edges(old, new)).exceptAll(new).count() == 0


def test_baselines_label_every_vertex(spark):
    e = graphs.planted(spark, 3, 20, 5, 1)
    n = 60
    for labels, most in (
        (baselines.stream_greedy(e, 3), 1.3), (baselines.stream_interpolated(e, 3), 1.2), (baselines.multilevel_partition(e, 3, coarse_target=20), 1.3),
        (baselines.coarsen_lpa_partition(e, 3, coarse_target=20), 1.8),
    ):
        rows = labels.collect()
        assert len({r.v for r in rows}) == len(rows) == n
        assert max(collections.Counter(r.label for r in rows).values()) <= math.ceil(most * n / 3)


def test_applications(spark):
    e = edges(spark, [(1, 2), (2, 3), (3, 1), (5, 6)])
    assert sorted((r.v, r.dist) for r in apps.sssp(e, 1).collect()) == [(1, 0), (2, 1), (3, 2)]
    assert {(r.v, r.component) for r in apps.wcc(e).collect()} == {(1, 1), (2, 1), (3, 1), (5, 5), (6, 5)}
    assert apps.pagerank(e, 3).agg(F.sum("rank")).first()[0] == pytest.approx(1)


def rows_of(df):
    return sorted(tuple(r) for r in df.collect())


def test_hubs_in_parts_change_nothing(spark):
    e = edges(spark, [(0, i) for i in range(1, 40)] + [(i, i % 39 + 1) for i in range(1, 40)])
    arcs = convert.to_weighted_undirected(e)
    verts = convert.vertex_stats(arcs)
    labels = st.init_random(verts, 3)
    plain = engine.run_loop(arcs, verts, labels, [0, 1, 2], halting=FixedIterations(3))
    parts = engine.run_loop(arcs, verts, labels, [0, 1, 2], halting=FixedIterations(3), hub=5)
    assert rows_of(plain.labels) == rows_of(parts.labels)
    laid = scores.lay_out(arcs, verts, 41, 5)
    assert laid.count() == arcs.count() and laid.where("src = 0").select("part").distinct().count() > 3


def test_no_iteration_exchanges_arcs(spark):
    e = graphs.small_world(spark, 200, 4, 0.3)
    arcs = convert.to_weighted_undirected(e)
    verts = convert.vertex_stats(arcs)
    laid = durable_as_dealt(scores.lay_out(arcs, verts, 100))
    before = {key: spark.conf.get(key) for key in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.enabled")}
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        plan = scores.build_hist(laid, durable(st.init_random(verts, 3)))._jdf.queryExecution().executedPlan().toString()
    finally:
        for key, x in before.items():
            spark.conf.set(key, x)
    lines = plan.splitlines()
    at = next(i for i, line in enumerate(lines) if "Scan ExistingRDD[src" in line)
    above = []  # operators between the arcs and the join
    for line in reversed(lines[:at]):
        if "Join" in line:
            break
        above.append(line)
    assert not any("Exchange" in line for line in above), plan


def test_old_files_are_released(spark):
    df = durable(spark.range(10))
    path = df._jdf.queryExecution().logical().rdd().getCheckpointFile().get().removeprefix("file:")
    assert os.path.isdir(path)
    release(df)
    assert not os.path.exists(path)


def test_uneven_capacities(spark):
    e = graphs.small_world(spark, 300, 4, 0.3)
    r = partition(e, 3, max_iter=5, capacity_weights={0: 2.0, 1: 1.0, 2: 1.0})
    last = r.loads[-1]
    assert sum(last.values()) == r.vertices.agg(F.sum("deg")).first()[0]
    assert last[0] > 1.5 * max(last[1], last[2])
    even = partition(e, 3, halting=FixedIterations(1))
    same = partition(e, 3, halting=FixedIterations(1), capacity_weights={0: 1.0, 1: 1.0, 2: 1.0})
    assert rows_of(even.labels) == rows_of(same.labels)
    with pytest.raises(ValueError):
        partition(e, 3, max_iter=1, capacity_weights={0: 1.0})


def test_out_degree_loads(spark):
    r = partition(edges(spark, [(1, 2), (1, 3), (2, 3), (4, 1)]), 2, unit="out_degree", max_iter=1)
    assert {x.v: x.odeg for x in r.vertices.collect()} == {1: 2, 2: 1, 3: 0, 4: 1}
    assert sum(r.loads[0].values()) == 4


def test_sequential_sweep_equals_a_plain_one(spark):
    e = [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 6), (6, 4), (7, 6), (8, 7), (8, 1)]
    r = partition(edges(spark, e), 2, c=1.2, halting=FixedIterations(1), async_mode="sequential", seed=3)
    near = collections.defaultdict(dict)
    for a, b in e:
        near[a][b] = near[b][a] = 1
    verts = spark.createDataFrame([(v,) for v in near], "v long")
    label = {x.v: x.label for x in st.init_random(verts, 2, 3).collect()}
    cap = 1.2 * 20 / 2
    load = {j: sum(len(near[v]) for v in near if label[v] == j) for j in (0, 1)}
    for v in sorted(near):
        s = {j: sum(1 for u in near[v] if label[u] == j) / len(near[v]) - load[j] / cap for j in (0, 1)}
        to = max(s, key=lambda j: (s[j], j == label[v], -j))
        if to != label[v] and load[to] + len(near[v]) <= cap:
            load[label[v]] -= len(near[v])
            load[to] += len(near[v])
            label[v] = to
    assert {x.v: x.label for x in r.labels.collect()} == label


def test_without_penalty_is_label_counting(spark):
    arcs, labels, state = f2(spark)
    r = engine.run_loop(arcs, convert.vertex_stats(arcs), labels, [0, 1], halting=FixedIterations(1), throttle="none", penalised=False)
    want = {1: 0, 2: 0, 3: 0, 4: 1, 5: 1, 6: 1}
    assert {x.v: x.label for x in r.labels.collect()} == want


def test_levels_are_refined_in_spark(spark):
    e = graphs.planted(spark, 3, 20, 5, 1)
    arcs = convert.to_weighted_undirected(e)
    nodes = convert.vertex_stats(arcs).select("v", F.col("deg").alias("weight"))
    labels = st.init_random(nodes, 3, 5)
    got = baselines._refine_in_spark(nodes, arcs, labels, 3, 1.2, 1)
    assert got.count() == 60
    assert metrics.cut_edges(e, got).first()["cut"] < metrics.cut_edges(e, labels).first()["cut"]


def test_messages_of_applications(spark):
    e = edges(spark, [(1, 2), (2, 3), (5, 6)])
    labels = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (5, 0), (6, 1)], "v long, label int")
    assert tuple(apps.messages_of("pagerank", e, labels).first()) == (3, 2)
    assert tuple(apps.messages_of("sssp", e, labels, apps.sssp(e, 1)).first()) == (2, 1)
    assert tuple(apps.messages_of("wcc", e, labels).first()) == (6, 4)
