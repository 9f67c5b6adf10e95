"""The experiments, re-expressed on the given tables: each returns a frame of measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphpart.operators import adapt, apps, baselines, convert, metrics
from graphpart.operators.engine import FixedIterations, partition
from graphpart.session import durable
from graphpart.sources import graphs


def _edges(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, bool]:
    return graphs.BUILDERS[name](spark, sf_dir).select("src", "dst"), name in graphs.DIRECTED


def quality_by_k(spark: SparkSession, sf_dir: str, names=("g_web", "g_conv"), ks=(2, 4, 8), max_iter: int = 12) -> DataFrame:
    """Phi, rho, iterations, and the gain over hash, for graphs and numbers of labels."""
    rows = []
    for name in names:
        e, directed = _edges(spark, sf_dir, name)
        for k in ks:
            r = partition(e, k, directed=directed, max_iter=max_iter)
            base = metrics.phi(convert.to_undirected(e), baselines.hash_partition(r.vertices, k, "mixed")).first()[0] or 1e-9
            h = r.history[-1]
            rows.append((name, k, h["phi"], h["rho"], h["t"], h["phi"] / base))
    return spark.createDataFrame(rows, "graph string, k int, phi double, rho double, iterations int, gain double")


def mean_rho(by_k: DataFrame) -> DataFrame:
    """Mean rho of each graph over k."""
    return by_k.groupBy("graph").agg(F.avg("rho").alias("mean_rho"))


def comparison(spark: SparkSession, sf_dir: str, name: str = "g_web", ks=(4, 8), max_iter: int = 16) -> DataFrame:
    """The method and the baselines on one graph."""
    e, directed = _edges(spark, sf_dir, name)
    e = durable(e)  # read once, not by each approach
    rows = []
    for k in ks:
        r = partition(e, k, directed=directed, max_iter=max_iter)
        made = {
            "method": r.labels,
            "hash": baselines.hash_partition(r.vertices, k, "mixed"),
            "stream_greedy": baselines.stream_greedy(e, k, directed=directed),
            "stream_interpolated": baselines.stream_interpolated(e, k, directed=directed),
            "multilevel": baselines.multilevel_partition(e, k, directed=directed, coarse_target=300),
            "coarsen_lpa": baselines.coarsen_lpa_partition(e, k, directed=directed, coarse_target=300),
        }
        for approach, labels in made.items():
            q = metrics.quality(e, labels, k, directed).first()
            rows.append((approach, k, q["phi"], q["rho"], q["rho_v"]))
    return spark.createDataFrame(rows, "approach string, k int, phi double, rho double, rho_v double")


def evolution(spark: SparkSession, sf_dir: str, name: str = "g_cust_supp", k: int = 8, iterations: int = 12) -> DataFrame:
    """Phi, rho and score by iteration, past the halt."""
    e, directed = _edges(spark, sf_dir, name)
    r = partition(e, k, directed=directed, halting=FixedIterations(iterations, record_halt=True))
    halted = -1 if r.halted_at is None else r.halted_at
    return r.history_frame(spark).select("t", "phi", "rho", "score", "messages", F.lit(halted).alias("halted_at"))


def effect_of_c(spark: SparkSession, sf_dir: str, name: str = "g_web", k: int = 8, cs=(1.02, 1.05, 1.10, 1.20), seeds=(1, 2), max_iter: int = 16) -> DataFrame:
    """Rho and iterations for each slack, over seeds."""
    e, directed = _edges(spark, sf_dir, name)
    rows = []
    for c in cs:
        for seed in seeds:
            h = partition(e, k, c=c, directed=directed, seed=seed, max_iter=max_iter).history[-1]
            rows.append((c, seed, h["rho"], h["t"]))
    got = spark.createDataFrame(rows, "c double, seed int, rho double, iterations int")
    return got.groupBy("c").agg(F.min("rho").alias("min_rho"), F.avg("rho").alias("mean_rho"), F.max("rho").alias("max_rho"), F.avg("iterations").alias("iterations"))


def runtime_by_size(spark: SparkSession, sizes=(1024, 4096), d: int = 40, beta: float = 0.3, k: int = 64, candidate_set: str = "compact") -> DataFrame:
    """Seconds of the first iteration by number of vertices."""
    rows = []
    for n in sizes:
        r = partition(graphs.small_world(spark, n, d, beta), k, halting=FixedIterations(1), candidate_set=candidate_set, most_local=0)
        rows.append((n, metrics.first_iteration_seconds(r)))
    return spark.createDataFrame(rows, "n int, seconds double")


def runtime_by_k(spark: SparkSession, ks=(2, 32, 128), n: int = 2048, d: int = 40, candidate_set: str = "all_k") -> DataFrame:
    """Seconds of the first iteration by number of labels."""
    e = graphs.small_world(spark, n, d, 0.3)
    rows = [(k, metrics.first_iteration_seconds(partition(e, k, halting=FixedIterations(1), candidate_set=candidate_set, most_local=0))) for k in ks]
    return spark.createDataFrame(rows, "k int, seconds double")


def runtime_by_workers(spark: SparkSession, workers=(1, 2, 4, 8), n: int = 16384, d: int = 40, k: int = 64) -> DataFrame:
    """Seconds of the first iteration and speed-up over the fewest workers.

    A session's cores are fixed, so w workers stand for w tasks at a time: the graph and every exchange have w partitions.
    """
    before = spark.conf.get("spark.sql.shuffle.partitions")
    rows = []
    try:
        for w in workers:
            spark.conf.set("spark.sql.shuffle.partitions", str(w))
            rows.append((w, metrics.first_iteration_seconds(partition(graphs.small_world(spark, n, d, 0.3).coalesce(w), k, halting=FixedIterations(1), most_local=0))))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return spark.createDataFrame([(w, s, rows[0][1] / s) for w, s in rows], "workers int, seconds double, speedup double")


def application_runtime(spark: SparkSession, sf_dir: str, name: str = "g_web", k: int = 8, max_iter: int = 12, steps: int = 5) -> DataFrame:
    """Seconds, messages and remote messages of three applications under hash and under the method, and what the method saves."""
    e, directed = _edges(spark, sf_dir, name)
    e = durable(e)
    r = partition(e, k, directed=directed, max_iter=max_iter)
    source = e.agg(F.min("src")).first()[0]
    runs = {"pagerank": lambda labels: apps.pagerank(e, steps, labels=labels), "sssp": lambda labels: apps.sssp(e, source), "wcc": lambda labels: apps.wcc(e)}
    cost: dict[tuple[str, str], tuple] = {}
    for approach, labels in (("hash", baselines.hash_partition(r.vertices, k, "mixed")), ("method", r.labels)):
        for app, run in runs.items():
            began = time.time()
            got = durable(run(labels)) if source is not None else None
            took = time.time() - began
            m = apps.messages_of(app, e, labels, got).first() if got is not None else {"messages": 0, "remote": 0}
            cost[app, approach] = (took, m["messages"], m["remote"])
    rows = []
    for app in runs:
        for approach in ("hash", "method"):
            (s0, _, r0), (s, n, remote) = cost[app, "hash"], cost[app, approach]
            rows.append((app, approach, s, n, remote, 1 - s / max(1e-9, s0), 1 - remote / max(1, r0)))
    return spark.createDataFrame(rows, "app string, approach string, seconds double, messages long, remote long, time_saved double, remote_saved double")


def with_slope(timed: DataFrame, by: str) -> DataFrame:
    """The times, and the slope of a line through them in log-log: 1 is in proportion, 0 no growth."""
    return timed.crossJoin(F.broadcast(timed.agg(F.regr_slope(F.log("seconds"), F.log(by)).alias("slope"))))  # one row


def graph_change(spark: SparkSession, sf_dir: str, name: str = "g_web", k: int = 8, shares=(0.005, 0.02, 0.1), max_iter: int = 16) -> DataFrame:
    """Savings and difference against a run from scratch, by share of new edges."""
    e, directed = _edges(spark, sf_dir, name)
    rows = []
    for share in shares:
        old, _ = adapt.holdout(e, share)
        before = partition(old, k, directed=directed, max_iter=max_iter)
        scratch = partition(e, k, directed=directed, seed=7, max_iter=max_iter)
        after = adapt.adapt_graph(before.labels, e, k, directed=directed, max_iter=max_iter)
        s = metrics.savings(after, scratch)
        rows.append((share, s["time"], s["messages"], metrics.partition_difference(before.labels, after.labels).first()[0], metrics.partition_difference(before.labels, scratch.labels).first()[0], after.history[-1]["phi"], after.history[-1]["rho"]))
    return spark.createDataFrame(rows, "share double, time_saved double, messages_saved double, difference double, difference_scratch double, phi double, rho double")


def label_change(spark: SparkSession, sf_dir: str, name: str = "g_web", k: int = 8, adds=(1, 2), max_iter: int = 16) -> DataFrame:
    """Savings and difference when labels are added (and one removed, add = -1)."""
    e, directed = _edges(spark, sf_dir, name)
    before = partition(e, k, directed=directed, max_iter=max_iter)
    rows = []
    for add in (*adds, -1):
        after = adapt.adapt_k(before.labels, e, before.label_set, add=max(add, 0), remove=[k - 1] if add < 0 else None, directed=directed, max_iter=max_iter)
        scratch = partition(e, k + add, directed=directed, seed=7, max_iter=max_iter)
        s = metrics.savings(after, scratch)
        rows.append((add, s["time"], s["messages"], metrics.partition_difference(before.labels, after.labels).first()[0], metrics.partition_difference(before.labels, scratch.labels).first()[0]))
    return spark.createDataFrame(rows, "add int, time_saved double, messages_saved double, difference double, difference_scratch double")


def worker_balance(spark: SparkSession, sf_dir: str, name: str = "g_web", k: int = 8, max_iter: int = 16) -> DataFrame:
    """Idle share and remote messages of PageRank under hash and under the method."""
    e, directed = _edges(spark, sf_dir, name)
    r = partition(e, k, directed=directed, max_iter=max_iter)
    rows = []
    for approach, labels in (("hash", baselines.hash_partition(r.vertices, k, "mixed")), ("method", r.labels)):
        w, m = metrics.idle_fraction(apps.worker_load(e, labels)).first(), apps.app_messages(e, labels).first()
        rows.append((approach, w["mean"], w["max"], w["min"], w["idle"], m["messages"], m["remote"]))
    return spark.createDataFrame(rows, "approach string, mean double, max double, min double, idle double, messages long, remote long")


def ablations(spark: SparkSession, sf_dir: str, name: str = "g_events", k: int = 8, iterations: int = 6) -> DataFrame:
    """One flag at a time, for a fixed number of iterations."""
    e, directed = _edges(spark, sf_dir, name)
    flags = {"default": {}, "naive_weights": {"weights": "naive"}, "unthrottled": {"throttle": "none"}, "no_penalty": {"penalised": False}, "per_task": {"async_mode": "per_task"}, "batched": {"async_mode": "batched"}}
    rows = []
    for flag, options in flags.items():
        r = partition(e, k, directed=directed, halting=FixedIterations(iterations), **options)
        h = r.history[-1]
        rows.append((flag, metrics.phi(e, r.labels).first()[0], h["rho"], r.messages))
    return spark.createDataFrame(rows, "flag string, phi double, rho double, messages long")


WORKLOADS = {
    "w01_quality_by_k": quality_by_k,
    "w02_gain_over_hash": lambda s, d: quality_by_k(s, d, names=("g_conv",), ks=(4, 16)).select("graph", "k", "phi", "gain"),
    "w03_mean_rho": lambda s, d: mean_rho(quality_by_k(s, d, names=("g_conv",), ks=(2, 4))),
    "w04_comparison": comparison,
    "w05_evolution": evolution,
    "w06_effect_of_c": lambda s, d: effect_of_c(s, d, cs=(1.02, 1.2), seeds=(1,)),
    "w07a_runtime_by_size": lambda s, d: with_slope(runtime_by_size(s, sizes=(1024, 4096, 16384)), "n"),
    "w07b_runtime_by_workers": lambda s, d: runtime_by_workers(s),
    "w07c_runtime_by_k": lambda s, d: with_slope(runtime_by_k(s), "k"),
    "w08_graph_change": lambda s, d: graph_change(s, d, shares=(0.02,)),
    "w09_stability": lambda s, d: graph_change(s, d, name="g_conv", shares=(0.005, 0.05)).select("share", "difference", "difference_scratch", F.lit(1 - 1 / 8).alias("difference_by_chance")),
    "w10_label_change": lambda s, d: label_change(s, d, adds=(1,)),
    "w11_worker_balance": worker_balance,
    "w12_application_runtime": application_runtime,
    "w15_ablations": lambda s, d: ablations(s, d, iterations=3),
}
