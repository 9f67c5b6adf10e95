"""Queries past the sizes that they once refused, and on the tables that they once left out."""

import collections

import duckdb
import numpy as np
import pytest

from graphpart.queries import ORACLE, QUERIES
from graphpart.sources import graphs
from graphpart.sources.tables import TABLES
from tests.conftest import SF
from tests.test_oracle import value


def by_sql(spark, name, sf_dir=SF):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = QUERIES[name](spark, sf_dir)
    cols = sorted(df.columns)
    want = con.sql(ORACLE[name]).select(*(f'"{c}"' for c in cols)).fetchall()
    got = df.select(cols).collect()
    assert collections.Counter(tuple(map(value, r)) for r in got) == collections.Counter(tuple(map(value, r)) for r in want)
    return got


def test_small_world_stands_on_customers(spark):
    rows = by_sql(spark, "graph_smallworld")
    keys = {r["c_custkey"] * 8 for r in spark.read.parquet(f"{SF}/customer.parquet").collect()}
    assert {v for r in rows for v in r} == keys


def test_overflow_bound_of_each_label(spark):
    rows = by_sql(spark, "overflow_bound")
    assert {r["eps"] for r in rows} == {0.2, 0.4} and "label" in rows[0].asDict()


def test_ranks_of_keys(spark):
    keys = [9, 2, 2, None, 70, 5, -1, 33]
    at, n = graphs.ranked(spark.createDataFrame([(i,) for i in keys], "key long"))
    assert n == 6 and sorted(tuple(r) for r in at.collect()) == [(x, i) for i, x in enumerate([-1, 2, 5, 9, 33, 70])]


@pytest.mark.parametrize("chunk", [37, 50_000])
def test_nearest_vectors_in_chunks(spark, tmp_path, chunk):
    rng = np.random.default_rng(3)
    m = rng.normal(size=(300, 16)).astype(np.float32)
    m[100:140] = m[:40]  # equal vectors tie, to the smaller id
    m[140:180] = 2 * m[:40]
    spark.createDataFrame([(i * 7, v.tolist()) for i, v in enumerate(m)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
    want = con.sql(ORACLE["graph_knn"]).fetchall()
    assert sorted(tuple(r) for r in graphs.g_knn(spark, str(tmp_path), chunk=chunk).collect()) == sorted(want)


@pytest.mark.parametrize("options", [{}, {"unit": "vertices"}, {"throttle": "none"}, {"capacity_weights": {0: 2.0, 1: 1.0, 2: 1.0, 3: 1.0}}, {"penalised": False}])
def test_small_graphs_in_one_task_get_the_same_labels(spark, options):
    from graphpart.operators.engine import FixedIterations, partition

    e = graphs.small_world(spark, 150, 3, 0.3)
    a, b = (partition(e, 4, halting=FixedIterations(3), most_local=most, **options) for most in (0, 10_000))
    assert sorted(a.labels.collect()) == sorted(b.labels.collect())
    for x, y in zip(a.history, b.history, strict=True):
        assert all(x[n] == y[n] for n in ("t", "phi", "rho", "candidates", "migrated", "messages", "max_load")) and abs(x["score"] - y["score"]) < 1e-9
    assert a.loads == b.loads


def test_multilevel_past_the_drivers_limit(spark, monkeypatch):
    from graphpart.operators import baselines

    monkeypatch.setattr(baselines, "MOST_COARSE", 20)
    e = spark.createDataFrame([(0, i) for i in range(1, 60)] + [(i, i + 1) for i in range(1, 59, 9)], "src long, dst long")
    for make in (baselines.multilevel_partition, baselines.coarsen_lpa_partition):
        got = make(e, 2, coarse_target=10).collect()
        assert sorted(r["v"] for r in got) == list(range(60)) and {r["label"] for r in got} <= {0, 1}


def size_bits(df):
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()).bit_length()


def test_estimates_of_sizes_stay_small_in_loops(spark):
    from graphpart.session import durable, durable_as_dealt, release

    x = spark.createDataFrame([(i, i % 3) for i in range(20)], "v long, label int")
    for _ in range(4):  # each round joins the frame with itself thrice, as loops over labels do
        x = durable(x.join(x.select("v"), "v").join(x.select("v"), "v").join(x.select("v"), "v").select("v", "label"))
        assert size_bits(x) <= 63
    assert sorted(tuple(r) for r in x.collect()) == [(i, i % 3) for i in range(20)]
    dealt = durable_as_dealt(x.join(x.select("v"), "v").repartition(3, "v"))
    assert size_bits(dealt) <= 63
    plan = dealt.groupBy("v").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan  # it still knows how it is dealt
    assert dealt.count() == 20
    release(dealt)


def test_coarsening_keeps_estimates_small(spark):
    from graphpart.operators import baselines

    got = baselines.coarsen_lpa_partition(graphs.small_world(spark, 60, 2, 0.3), 2, coarse_target=20)
    assert size_bits(got) <= 63 and got.count() == 60


def test_coarse_graphs_stay_out_of_the_driver(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    from graphpart.operators import baselines

    e = graphs.small_world(spark, 150, 2, 0.3)
    with monkeypatch.context() as m:
        m.setattr(DataFrame, "collect", lambda self: pytest.fail("rows of the graph go to the driver"))
        got = baselines.multilevel_partition(e, 4, coarse_target=100)
    rows = got.collect()
    assert sorted(r["v"] for r in rows) == list(range(150)) and {r["label"] for r in rows} == {0, 1, 2, 3}
