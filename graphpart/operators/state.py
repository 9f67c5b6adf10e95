"""Labels, loads, capacity, penalty. Labels are (v, label), loads (label, b, n); loads are k rows and may go to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.functions.draws import draw

UNITS = {"degree": "deg", "weighted_degree": "wdeg", "out_degree": "odeg", "vertices": None}


def load_of(unit: str):
    """The load of one vertex, as a column of vertices."""
    if unit not in UNITS:
        raise ValueError(f"unit is one of {sorted(UNITS)}")
    return F.lit(1).cast("long") if UNITS[unit] is None else F.col(UNITS[unit])


def init_random(vertices: DataFrame, k: int, seed: int = 42, provider: str = "fast") -> DataFrame:
    """A label for each vertex, a function of its id alone."""
    return vertices.select("v", F.pmod(draw(provider, seed, 0, "init", "v"), F.lit(k)).cast("int").alias("label"))


def init_from(labels: DataFrame, vertices: DataFrame, new_vertices: str = "least_loaded", k: int | None = None, seed: int = 42, provider: str = "fast", unit: str = "degree", active: list[int] | None = None) -> DataFrame:
    """Old labels for the vertices that have one; a policy for the others; vertices that are gone drop out.

    least_loaded: the least loaded label under the old labelling (ties: the smallest). random: a draw.
    water_fill: newcomers in id order fill the labels from the least loaded up, so that none is overfilled.
    """
    ids = sorted(active) if active is not None else list(range(k if k is not None else labels.agg(F.max("label")).first()[0] + 1))
    rows = vertices.join(labels.select("v", "label"), "v", "left")
    if new_vertices == "random":
        fresh = F.element_at(F.array(*map(F.lit, ids)), F.pmod(draw(provider, seed, 0, "new", "v"), F.lit(len(ids))).cast("int") + 1)
        return rows.select("v", F.coalesce("label", fresh).cast("int").alias("label"))
    known = rows.where("label IS NOT NULL")
    loads = {i: 0 for i in ids} | {r["label"]: r["b"] for r in partition_loads(known, unit=unit).collect() if r["label"] in set(ids)}
    if new_vertices == "least_loaded":
        return rows.select("v", F.coalesce("label", F.lit(min(ids, key=lambda i: (loads[i], i)))).cast("int").alias("label"))
    if new_vertices != "water_fill":
        raise ValueError("new_vertices is least_loaded, random or water_fill")
    from pyspark.sql import Window

    fresh = rows.where("label IS NULL").withColumn("load", load_of(unit))
    # running sums by hashed range, then within: no single task sees all newcomers
    fresh = fresh.withColumn("part", F.pmod(F.xxhash64("v"), F.lit(64)))
    sums = {r["part"]: r["s"] or 0 for r in fresh.groupBy("part").agg(F.sum("load").alias("s")).collect()}
    before, total = {}, 0
    for p in sorted(sums):
        before[p], total = total, total + sums[p]
    level = _water_level([loads[i] for i in ids], total)
    bounds, at = [], 0.0
    for i in ids:
        at += max(0.0, level - loads[i])
        bounds.append(at)
    base = F.element_at(F.array(*(F.lit(before.get(p, 0)) for p in range(64))), F.col("part").cast("int") + 1)
    position = base + F.sum("load").over(Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)) - F.col("load")
    place = F.lit(ids[-1])
    for i, bound in reversed(list(zip(ids, bounds, strict=True))):
        place = F.when(position < F.lit(bound), F.lit(i)).otherwise(place)
    return known.select("v", F.col("label").cast("int").alias("label")).union(fresh.select("v", place.cast("int").alias("label")))


def _water_level(loads: list[int], total: int) -> float:
    """The level up to which ``total`` fills the lowest loads."""
    low = sorted(loads)
    for n in range(1, len(low) + 1):
        level = (total + sum(low[:n])) / n
        if n == len(low) or level <= low[n]:
            return level
    return 0.0


def partition_loads(state: DataFrame, unit: str = "degree", label_set: list[int] | None = None) -> DataFrame:
    """(label, b, n) of (v, label, deg, wdeg); with ``label_set``, labels without members too."""
    loads = state.groupBy("label").agg(F.sum(load_of(unit)).alias("b"), F.count(F.lit(1)).alias("n"))
    if label_set is None:
        return loads
    zero = F.lit(0).cast("long")
    ids = state.sparkSession.createDataFrame([(i,) for i in label_set], "label int")
    return ids.join(loads, "label", "left").select("label", F.coalesce("b", zero).alias("b"), F.coalesce("n", zero).alias("n"))


def capacity(total: float, k: int, c: float = 1.05) -> float:
    if c <= 1:
        raise ValueError("c must be over 1")
    return c * total / k


def capacities(total: float, label_set: list[int], c: float = 1.05, weights: dict[int, float] | None = None) -> dict[int, float]:
    """The capacity of each label: even, or in proportion to positive ``weights`` of all labels."""
    if weights is None:
        return dict.fromkeys(label_set, capacity(total, len(label_set), c))
    if set(weights) != set(label_set) or min(weights.values()) <= 0:
        raise ValueError("capacity_weights needs a positive weight for every label")
    whole = sum(weights.values())
    return {i: capacity(total, 1, c) * weights[i] / whole for i in label_set}


def penalty(loads: DataFrame, cap: float) -> DataFrame:
    """(label, pi): the fill of each label; over 1 where it is overfull."""
    return loads.select("label", (F.col("b").cast("double") / F.lit(cap)).alias("pi"))


def remaining(loads: DataFrame, cap: float) -> DataFrame:
    """(label, r): free capacity; below 0 where it is overfull."""
    return loads.select("label", (F.lit(cap) - F.col("b").cast("double")).alias("r"))
