"""Quality, cost and stability measures."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphpart.operators import convert
from graphpart.operators import state as st
from graphpart.operators.engine import PartitionResult


def with_labels(edges: DataFrame, labels: DataFrame) -> DataFrame:
    a = labels.select(F.col("v").alias("src"), F.col("label").alias("src_label"))
    b = labels.select(F.col("v").alias("dst"), F.col("label").alias("dst_label"))
    return edges.join(a, "src").join(b, "dst")


def phi(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: share of edges inside a label."""
    return with_labels(edges, labels).agg(F.round(F.avg((F.col("src_label") == F.col("dst_label")).cast("double")), 6).alias("phi"))


def phi_weighted(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: share of arc weight inside a label; of reciprocal weights, the share of directed edges."""
    hit = F.when(F.col("src_label") == F.col("dst_label"), F.col("w")).otherwise(0)
    return with_labels(arcs, labels).agg(F.round(F.sum(hit) / F.sum("w"), 6).alias("phi"))


def rho(state: DataFrame, k: int, unit: str = "degree") -> DataFrame:
    """One row: the largest load over the even load."""
    loads = st.partition_loads(state, unit)
    return loads.agg(F.round(F.max("b") * F.lit(float(k)) / F.sum("b"), 6).alias("rho"))


def quality(edges: DataFrame, labels: DataFrame, k: int, directed: bool = True, c: float = 1.05) -> DataFrame:
    """One row: phi, phi_w, rho, rho_v, cut."""
    arcs = convert.to_weighted_undirected(edges, directed)
    marked = with_labels(arcs, labels)
    same = (F.col("src_label") == F.col("dst_label")).cast("int")
    a = marked.agg(F.round(F.avg(same), 6).alias("phi"), F.round(F.sum(same * F.col("w")) / F.sum("w"), 6).alias("phi_w"), (F.sum(1 - same) / 2).cast("long").alias("cut"))
    loads = marked.groupBy("src_label").agg(F.count(F.lit(1)).alias("b"), F.count_distinct("src").alias("n"))
    b = loads.agg(F.round(F.max("b") * F.lit(float(k)) / F.sum("b"), 6).alias("rho"), F.round(F.max("n") * F.lit(float(k)) / F.sum("n"), 6).alias("rho_v"))
    return a.crossJoin(b)  # one row each


def cut_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return with_labels(edges, labels).agg(F.count_if(F.col("src_label") != F.col("dst_label")).alias("cut"), F.count(F.lit(1)).alias("edges"))


def cut_matrix(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(src_label, dst_label, n) with subtotals (null labels)."""
    return with_labels(edges, labels).rollup("src_label", "dst_label").agg(F.count(F.lit(1)).alias("n"))


def partition_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: share of the common vertices whose labels differ."""
    both = a.select("v", F.col("label").alias("la")).join(b.select("v", F.col("label").alias("lb")), "v")
    return both.agg(F.round(F.avg((F.col("la") != F.col("lb")).cast("double")), 6).alias("difference"), F.count(F.lit(1)).alias("vertices"))


def confusion(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.select("v", F.col("label").alias("la")).join(b.select("v", F.col("label").alias("lb")), "v")
    return both.groupBy("la", "lb").agg(F.count(F.lit(1)).alias("n"))


def align_labels(a: DataFrame, b: DataFrame) -> DataFrame:
    """b with its labels renamed greedily to those of a they share most vertices with (k^2 rows on the driver)."""
    rows = sorted(confusion(a, b).collect(), key=lambda r: (-r["n"], r["la"], r["lb"]))
    to: dict[int, int] = {}
    for r in rows:
        if r["lb"] not in to and r["la"] not in to.values():
            to[r["lb"]] = r["la"]
    free = (i for i in range(10**9) if i not in set(to.values()))
    for r in rows:
        if r["lb"] not in to:
            to[r["lb"]] = next(free)
    table = F.create_map(*(x for k, v in sorted(to.items()) for x in (F.lit(k), F.lit(v))))
    return b.select("v", F.element_at(table, F.col("label")).alias("label"))


def boundary_vertices(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(v, remote_degree) of vertices with an edge to another label."""
    arcs = with_labels(convert.to_undirected(edges), labels)
    return arcs.where("src_label <> dst_label").groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("remote_degree"))


def induced(edges: DataFrame, labels: DataFrame, label: int) -> DataFrame:
    return with_labels(edges, labels).where((F.col("src_label") == label) & (F.col("dst_label") == label)).select("src", "dst")


def top_hubs(arcs: DataFrame, n: int = 10) -> DataFrame:
    return convert.vertex_stats(arcs).select("v", "deg").orderBy(F.desc("deg"), "v").limit(n)


def locality_gain(edges: DataFrame, labels: DataFrame, base: DataFrame) -> DataFrame:
    """One row: phi of labels over phi of base."""
    a, b = phi(edges, labels), phi(edges, base).withColumnRenamed("phi", "phi_base")
    return a.crossJoin(b).select("phi", "phi_base", F.round(F.try_divide("phi", "phi_base"), 6).alias("gain"))


def savings(adapted: PartitionResult, scratch: PartitionResult) -> dict[str, float]:
    """Shares of time, messages and iterations saved against a run from scratch."""
    secs = lambda r: sum(h["compute_s"] + h["migrate_s"] for h in r.history)
    return {
        "time": 1 - secs(adapted) / max(1e-9, secs(scratch)),
        "messages": 1 - adapted.messages / max(1, scratch.messages),
        "iterations": 1 - adapted.iterations / max(1, scratch.iterations),
    }


def first_iteration_seconds(r: PartitionResult) -> float:
    """Score step and migration step of the first iteration."""
    return r.history[0]["compute_s"] + (r.history[1]["migrate_s"] if len(r.history) > 1 else 0.0)


def loglog_slope(points: list[tuple[float, float]]) -> float:
    xs, ys = [math.log(x) for x, _ in points], [math.log(y) for _, y in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)


def idle_fraction(worker_times: DataFrame) -> DataFrame:
    """From (step, label, work): mean, max and min over labels a step, averaged over steps with deviations; idle = 1 - mean/max."""
    step = worker_times.groupBy("step").agg(F.avg("work").alias("a"), F.max("work").alias("hi"), F.min("work").alias("lo"))
    r = lambda c: F.round(c, 6)
    return step.agg(
        r(F.avg("a")).alias("mean"), r(F.coalesce(F.stddev("a"), F.lit(0.0))).alias("mean_sd"), r(F.avg("hi")).alias("max"), r(F.coalesce(F.stddev("hi"), F.lit(0.0))).alias("max_sd"),
        r(F.avg("lo")).alias("min"), r(F.coalesce(F.stddev("lo"), F.lit(0.0))).alias("min_sd"), r(1 - F.avg("a") / F.avg("hi")).alias("idle"),
    )


def quality_cube(edges: DataFrame, labels: DataFrame, vertices: DataFrame) -> DataFrame:
    """(kind, label, vertices, load, remote): members, degrees and arcs to other labels by kind of vertex and label, with all subtotals (null)."""
    remote = with_labels(convert.to_undirected(edges), labels).groupBy(F.col("src").alias("v")).agg(F.count_if(F.col("src_label") != F.col("dst_label")).alias("remote"))
    rows = vertices.join(labels, "v").join(remote, "v").select(F.pmod("v", F.lit(8)).alias("kind"), "label", "deg", "remote")
    return rows.cube("kind", "label").agg(F.count(F.lit(1)).alias("vertices"), F.sum("deg").alias("load"), F.sum("remote").alias("remote"))


def patience_window(history: DataFrame, n_vertices: int, eps: float, patience: int) -> DataFrame:
    """(t, score, stagnant): the score a vertex, and whether the last ``patience`` gains are all at most ``eps``. A history has a row an iteration, so one task holds it."""
    x = history.select("t", (F.col("score") / F.lit(max(1, n_vertices))).alias("x"))
    gains = x.withColumn("g", F.col("x") - F.lag("x").over(Window.orderBy("t")))
    last = Window.orderBy("t").rowsBetween(1 - patience, 0)
    return gains.select("t", F.round("x", 6).alias("score"), ((F.count("g").over(last) == patience) & F.coalesce(F.max("g").over(last) <= eps, F.lit(False))).alias("stagnant"))


def repeat(run, seeds: list[int]) -> dict[str, float]:
    """min, mean and max of a number over seeds."""
    xs = [run(s) for s in seeds]
    return {"min": min(xs), "mean": sum(xs) / len(xs), "max": max(xs)}


def within_slack(rho_value: float, c: float) -> dict[str, float | bool]:
    return {"unbalance_percent": (rho_value - 1) * 100, "within": rho_value <= c}
