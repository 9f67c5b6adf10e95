"""Baselines against plain versions on small graphs, and invariants of the variants."""

import collections

import pytest
from pyspark.sql import functions as F

from graphpart.operators import baselines, convert
from graphpart.operators import state as st
from graphpart.operators.engine import FixedIterations, partition
from graphpart.sources import graphs


def adjacency(e):
    near = collections.defaultdict(set)
    for r in e.collect():
        if r.src != r.dst:
            near[r.src].add(r.dst)
            near[r.dst].add(r.src)
    return near


def labels_of(df):
    rows = df.collect()
    assert len({r.v for r in rows}) == len(rows)
    return {r.v: r.label for r in rows}


def test_greedy_stream_equals_a_plain_pass(spark):
    e = graphs.planted(spark, 3, 14, 4, 1)
    near, k = adjacency(e), 3
    cap = 1.05 * sum(map(len, near.values())) / k
    want, load = {}, [0] * k
    for v in sorted(near):
        rank = []
        for j in range(k):
            if load[j] < cap:
                rank.append((sum(want.get(u) == j for u in near[v]) * (1 - load[j] / cap), -load[j], -j))
        want[v] = -max(rank)[2]
        load[want[v]] += len(near[v])
    assert labels_of(baselines.stream_greedy(e, k, order="natural")) == want


def test_interpolated_stream_equals_a_plain_pass(spark):
    e = graphs.planted(spark, 3, 14, 4, 2)
    near, k = adjacency(e), 3
    n = len(near)
    alpha = sum(map(len, near.values())) / 2 * k**0.5 / n**1.5
    want, size = {}, [0] * k
    for v in sorted(near):
        rank = []
        for j in range(k):
            if size[j] + 1 <= 1.1 * n / k:
                rank.append((sum(want.get(u) == j for u in near[v]) - alpha * 1.5 * size[j] ** 0.5, -size[j], -j))
        want[v] = -max(rank)[2]
        size[want[v]] += 1
    assert labels_of(baselines.stream_interpolated(e, k, order="natural", unit="vertices")) == want


def test_one_label_holds_all(spark):
    e = graphs.planted(spark, 2, 10, 3, 1)
    for make in (baselines.stream_greedy, baselines.stream_interpolated, baselines.central_lpa):
        assert set(labels_of(make(e, 1)).values()) == {0}


def test_central_plan_keeps_the_balance_and_gains(spark):
    e = graphs.planted(spark, 3, 20, 6, 1)
    near = adjacency(e)
    local = lambda x: sum(x[v] == x[u] for v in near for u in near[v])
    first = labels_of(st.init_random(convert.vertex_stats(convert.to_undirected(e)), 3))
    last = labels_of(baselines.central_lpa(e, 3, iterations=6))
    assert set(last) == set(near)
    assert local(last) > local(first)


def test_mini_batches_label_all_within_the_room(spark):
    e = graphs.planted(spark, 4, 50, 6, 1)
    near = adjacency(e)
    got = labels_of(baselines.stream_greedy(e, 4, batches=5))
    assert set(got) == set(near)
    load = collections.Counter()
    for v, j in got.items():
        load[j] += len(near[v])
    assert max(load.values()) <= 1.4 * sum(load.values()) / 4


def test_newcomers_fill_the_lowest_labels(spark):
    verts = spark.createDataFrame([(v, 2, 2) for v in range(400)], "v long, deg long, wdeg long")
    old = spark.createDataFrame([(v, 0) for v in range(100)] + [(v, 1) for v in range(100, 140)], "v long, label int")
    got = labels_of(st.init_from(old, verts, "water_fill", 3))
    assert all(got[v] == (0 if v < 100 else 1) for v in range(140))
    load = collections.Counter(got.values())
    assert max(load.values()) - min(load.values()) <= 2 and sum(load.values()) == 400


@pytest.mark.parametrize("options", [{"async_mode": "per_task"}, {"async_mode": "per_task", "unit": "weighted_degree"}, {"async_mode": "batched"}])
def test_variants_keep_vertices_and_loads(spark, options):
    e = graphs.planted(spark, 3, 25, 5, 1)
    r = partition(e, 3, halting=FixedIterations(4), **options)
    whole = r.vertices.agg(F.sum("wdeg" if options.get("unit") else "deg")).first()[0]
    assert all(sum(x.values()) == whole for x in r.loads)
    assert labels_of(r.labels).keys() == adjacency(e).keys()
    assert r.history[-1]["phi"] > r.history[0]["phi"]


def test_a_run_halts_by_the_rule(spark):
    e = graphs.planted(spark, 3, 25, 5, 1)
    r = partition(e, 3, eps=0.01, patience=3, max_iter=100)
    assert r.iterations < 100
    x = [h["score"] / 75 for h in r.history]
    assert all(b - a <= 0.01 + 1e-9 for a, b in zip(x[-4:], x[-3:]))
    assert r.history[-1]["phi"] > r.history[0]["phi"]
