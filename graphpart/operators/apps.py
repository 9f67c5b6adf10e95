"""Applications that use a partitioning: PageRank, shortest paths, components, over one superstep harness with message counts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphpart.operators import convert
from graphpart.operators.metrics import with_labels
from graphpart.session import durable


def superstep(state: DataFrame, edges: DataFrame, send: Column, combine: Callable[[Column], Column], local_first: bool = False, labels: DataFrame | None = None) -> DataFrame:
    """(v, message): what vertices of ``state`` (v, ...) send along out-edges, combined by receiver.

    With local_first and labels, messages are first combined by (receiver, sender's label), so a label sends one row a receiver.
    """
    sent = state.join(edges.select(F.col("src").alias("v"), "dst"), "v").select("dst", "v", send.alias("m"))
    if local_first and labels is not None:
        sent = sent.join(labels.select("v", "label"), "v").groupBy("dst", "label").agg(combine(F.col("m")).alias("m"))
    return sent.groupBy(F.col("dst").alias("v")).agg(combine(F.col("m")).alias("message"))


def pagerank(edges: DataFrame, iters: int = 20, d: float = 0.85, labels: DataFrame | None = None, cut_every: int = 5) -> DataFrame:
    """(v, rank) after ``iters`` iterations; the mass of vertices without out-edges is spread evenly."""
    e = durable(convert.validate_edges(edges))
    verts = e.select(F.col("src").alias("v")).union(e.select(F.col("dst").alias("v"))).distinct()
    out = e.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("out"))
    base = durable(verts.join(out, "v", "left"))
    n = base.count()
    ranks = base.withColumn("rank", F.lit(1.0 / max(1, n)))
    for i in range(iters):
        loose = ranks.agg(F.coalesce(F.sum(F.when(F.col("out").isNull(), F.col("rank"))), F.lit(0.0)).alias("loose"))
        got = superstep(ranks.where("out IS NOT NULL"), e, F.col("rank") / F.col("out"), F.sum, labels is not None, labels)
        nxt = base.join(got, "v", "left").join(F.broadcast(loose))  # one row
        ranks = nxt.select("v", "out", (F.lit((1 - d) / max(1, n)) + F.lit(d) * (F.coalesce("message", F.lit(0.0)) + F.col("loose") / F.lit(float(n)))).alias("rank"))
        if i % cut_every == cut_every - 1:
            ranks = durable(ranks)
    return ranks.select("v", "rank")


def sssp(edges: DataFrame, source: int, weighted: bool = False, max_steps: int = 10_000) -> DataFrame:
    """(v, dist) of the vertices reached from ``source``: breadth first along out-edges, or by edge weight w."""
    if weighted:
        e = durable(edges.select("src", "dst", "w"))
    else:
        e = durable(convert.validate_edges(edges).withColumn("w", F.lit(1)))
    spark = edges.sparkSession
    dist = spark.createDataFrame([(source, 0)], "v long, dist long")
    front = dist
    for _ in range(max_steps):
        reach = front.join(e.withColumnRenamed("src", "v"), "v").groupBy("dst").agg(F.min(F.col("dist") + F.col("w")).alias("d"))
        better = reach.join(dist.withColumnsRenamed({"v": "dst", "dist": "old"}), "dst", "left").where("old IS NULL OR d < old")
        front = durable(better.select(F.col("dst").alias("v"), F.col("d").cast("long").alias("dist")))
        if front.isEmpty():
            break
        dist = durable(dist.union(front).groupBy("v").agg(F.min("dist").alias("dist")))
    return dist


def wcc(edges: DataFrame) -> DataFrame:
    """(v, component): the smallest id of the weakly connected component, by min-label propagation with label shortcuts."""
    arcs = durable(convert.to_undirected(edges).select("src", "dst"))
    comp = durable(arcs.groupBy(F.col("src").alias("v")).agg(F.least(F.min("dst"), F.col("src")).alias("component")))
    while True:
        near = comp.withColumnRenamed("v", "src").join(arcs, "src").groupBy(F.col("dst").alias("v")).agg(F.min("component").alias("m"))
        nxt = comp.join(near, "v").select("v", "component", F.least("m", "component").alias("low"))
        hop = nxt.select(F.col("v").alias("low"), F.col("low").alias("far"))
        nxt = durable(nxt.join(hop, "low", "left").select("v", "component", F.least("low", F.coalesce("far", "low")).alias("new")))
        changed = nxt.where("new <> component").limit(1).count()
        comp = nxt.select("v", F.col("new").alias("component"))
        if not changed:
            return comp


def app_messages(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: messages of one PageRank step, and those that leave a label."""
    return with_labels(convert.validate_edges(edges), labels).agg(F.count(F.lit(1)).alias("messages"), F.count_if(F.col("src_label") != F.col("dst_label")).alias("remote"))


def messages_of(app: str, edges: DataFrame, labels: DataFrame, result: DataFrame | None = None) -> DataFrame:
    """One row: messages of an application's run, and those that leave a label.

    pagerank: one message an edge and step (a step's count). sssp: a vertex tells its out-neighbours once, when it is
    reached (``result`` holds those reached). wcc: one message an arc and round (a round's count).
    """
    sent = convert.to_undirected(edges).select("src", "dst") if app == "wcc" else convert.validate_edges(edges)
    if app == "sssp":
        sent = sent.join(result.select(F.col("v").alias("src")), "src", "left_semi")
    return with_labels(sent, labels).agg(F.count(F.lit(1)).alias("messages"), F.count_if(F.col("src_label") != F.col("dst_label")).alias("remote"))


def worker_load(edges: DataFrame, labels: DataFrame, steps: int = 20) -> DataFrame:
    """(step, label, work): edges scanned and messages received by each label's vertices in each PageRank superstep."""
    m = with_labels(convert.validate_edges(edges), labels)
    out = m.groupBy(F.col("src_label").alias("label")).agg(F.count(F.lit(1)).alias("x"))
    into = m.groupBy(F.col("dst_label").alias("label")).agg(F.count(F.lit(1)).alias("x"))
    work = out.union(into).groupBy("label").agg(F.sum("x").alias("work"))
    return work.withColumn("step", F.explode(F.sequence(F.lit(1), F.lit(steps))))
