"""The streaming module against batch runs of the same rows."""

import datetime as dt

from pyspark.sql import functions as F

from graphpart.operators.engine import partition
from graphpart.sources import graphs
from graphpart.streaming import adaptive
from tests.conftest import SF


def drained(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    try:
        q.awaitTermination(120)
    finally:
        q.stop()
    return stream.sparkSession.table(name)


def test_windows_and_sessions_equal_batch(spark, tmp_path):
    spark.read.parquet(f"{SF}/events.parquet").repartitionByRange(4, "ts").write.parquet(str(tmp_path / "in"))
    events = adaptive.stream_events(spark, str(tmp_path / "in"))
    batch = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    for name, stream, same in (
        ("t_tumbling", adaptive.edge_rate(events), adaptive.edge_rate(batch)),
        ("t_sliding", adaptive.edge_rate(events, "2 days", "1 day"), adaptive.edge_rate(batch, "2 days", "1 day")),
        ("t_sessions", adaptive.session_counts(events), adaptive.session_counts(batch)),
    ):
        got, want = ({tuple(r) for r in df.collect()} for df in (drained(stream, name, "complete"), same))
        assert got == want and want


def test_first_edges_keeps_one_of_each(spark, tmp_path):
    at = dt.datetime(2001, 1, 1)
    spark.createDataFrame([(1, 2, at), (1, 2, at), (2, 3, at)], "src long, dst long, ts timestamp").coalesce(1).write.parquet(str(tmp_path / "in"))
    edges = spark.readStream.schema("src long, dst long, ts timestamp").parquet(str(tmp_path / "in"))
    assert sorted((r.src, r.dst) for r in drained(adaptive.first_edges(edges), "t_first").collect()) == [(1, 2), (2, 3)]


def test_batches_of_edges_adapt_the_stored_labels(spark, tmp_path):
    e = graphs.planted(spark, 3, 12, 4, 1)
    old, new = e.where("(src + dst) % 5 <> 0"), e.where("(src + dst) % 5 = 0")
    adaptive.start_state(partition(old, 3, max_iter=2).labels, old, str(tmp_path / "state"), 3)
    new.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("src long, dst long").parquet(str(tmp_path / "in"))
    q = adaptive.stream_adapt(stream, str(tmp_path / "state"), 3, str(tmp_path / "check"), iterations=1).trigger(availableNow=True).start()
    try:
        q.awaitTermination(180)
    finally:
        q.stop()
    labels, manifest = adaptive.load_state(spark, str(tmp_path / "state" / "1"))
    ends = e.select(F.col("src").alias("v")).union(e.select("dst")).distinct()
    assert manifest["t"] == 1
    assert labels.join(ends, "v").count() == ends.count() == labels.count()
    assert spark.read.parquet(str(tmp_path / "state" / "1" / "edges")).count() == e.distinct().count()


def test_new_vertices_and_monitor(spark):
    v = spark.createDataFrame([(1, 2, 2), (2, 1, 1), (3, 1, 1)], "v long, deg long, wdeg long")
    labels = spark.createDataFrame([(1, 0), (2, 1)], "v long, label int")
    got = {r.v: r.label for r in adaptive.stream_assign(v, labels, 2).collect()}
    assert got == {1: 0, 2: 1, 3: 1}
    edges = spark.createDataFrame([(1, 2), (1, 3)], "src long, dst long")
    row = adaptive.quality_monitor(edges, adaptive.stream_assign(v, labels, 2), v, 2).first()
    assert row["phi"] == 0 and row["rho"] == 1
