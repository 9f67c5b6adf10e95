"""Overflow bounds of throttled migration, and the dynamics of the load vector."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphpart.operators.engine import PartitionResult


def overflow_bound(n: int, r: float, eps: float, dmin: float, dmax: float) -> float:
    """The printed bound on the chance that inflow exceeds the free capacity r by eps * r, for n candidates of degrees dmin..dmax."""
    if dmax == dmin or n == 0:
        return 0.0
    return math.exp(-2 * n * (eps * r / (dmax - dmin)) ** 2)


def overflow_bound_column(n: Column, r: Column, eps: Column, dmin: Column, dmax: Column) -> Column:
    """``overflow_bound`` for each row."""
    none = (dmax == dmin) | (n == 0)
    return F.when(none, F.lit(0.0)).otherwise(F.exp(-2 * n * F.pow(eps * r / F.when(none, F.lit(None)).otherwise(dmax - dmin), 2)))


def overflow_bound_sum(sum_deg2: float, r: float, eps: float) -> float:
    """Hoeffding's bound for the sum of independent moves, each 0 or its degree."""
    return math.exp(-2 * (eps * r) ** 2 / sum_deg2) if sum_deg2 else 0.0


def overflow_bound_sum_column(sum_deg2: Column, r: Column, eps: float) -> Column:
    return F.exp(-2 * F.pow(F.lit(eps) * r, 2) / sum_deg2)


def overflow_rate(result: PartitionResult) -> float:
    """Share of iterations in which the largest load exceeds the capacity."""
    over = [h["max_load"] > result.capacity for h in result.history[1:]]
    return sum(over) / len(over) if over else 0.0


def overflow_frequency(spark, result: PartitionResult, eps: float) -> DataFrame:
    """(t, label, r, b, over, beyond, bound) of a run with record_flows: the load after iteration t, whether it exceeds the capacity, and the capacity by eps times what was free, beside the bound on that."""
    after = result.loads_frame(spark).join(result.bounds_frame(spark), ["t", "label"])
    cap = F.lit(float(result.capacity))
    bound = overflow_bound_sum_column(F.col("sum_deg2"), F.col("r"), eps)
    return after.select("t", "label", F.round("r", 6).alias("r"), "b", (F.col("b") > cap).alias("over"), (F.col("b") > cap + F.lit(eps) * F.col("r")).alias("beyond"), F.round(bound, 6).alias("bound"))


def flow_matrix(flows: DataFrame, loads: DataFrame) -> DataFrame:
    """(t, from_label, to_label, x): row-stochastic transfer of loads (t, label, b), what stays on the diagonal."""
    out = flows.groupBy("t", "from_label").agg(F.sum("load").alias("out"))
    stay = loads.select("t", F.col("label").alias("from_label"), "b").join(out, ["t", "from_label"], "left")
    diag = stay.select("t", "from_label", F.col("from_label").alias("to_label"), (F.col("b") - F.coalesce("out", F.lit(0))).alias("load"))
    rows = flows.select("t", "from_label", "to_label", "load").union(diag)
    return rows.join(loads.select("t", F.col("label").alias("from_label"), "b"), ["t", "from_label"]).where("b > 0").select("t", "from_label", "to_label", F.round(F.col("load") / F.col("b"), 6).alias("x"))


def is_b_connected(flows: list[dict], labels: list[int], window: int) -> bool:
    """Whether the union of the transfer graphs of every ``window`` iterations in a row is connected."""
    if not flows:
        return len(labels) <= 1
    last = max(f["t"] for f in flows)
    for lo in range(1, last - window + 2):
        parent = {i: i for i in labels}

        def find(x: int, parent: dict[int, int] = parent) -> int:
            while parent[x] != x:
                x = parent[x]
            return x

        for f in flows:
            if lo <= f["t"] < lo + window:
                parent[find(f["from_label"])] = find(f["to_label"])
        if len({find(i) for i in labels}) > 1:
            return False
    return True


def load_distance(loads_by_t: list[list[float]]) -> list[float]:
    """Largest deviation from the even load at each iteration, over the largest load of the first."""
    even = sum(loads_by_t[0]) / len(loads_by_t[0])
    top = max(map(abs, loads_by_t[0]))
    return [max(abs(x - even) for x in row) / top for row in loads_by_t]


def decay_fit(distances: list[float]) -> float:
    """Rate mu of a geometric decay, by least squares on the logarithms."""
    points = [(t, math.log(d)) for t, d in enumerate(distances) if d > 0]
    if len(points) < 2:
        return 0.0
    mt, md = sum(t for t, _ in points) / len(points), sum(d for _, d in points) / len(points)
    return math.exp(sum((t - mt) * (d - md) for t, d in points) / sum((t - mt) ** 2 for t, _ in points))
