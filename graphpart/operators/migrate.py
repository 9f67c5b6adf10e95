"""Who may move: candidates ask, and move with the probability that keeps the expected inflow within the free capacity."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.functions.draws import RANGE, draw
from graphpart.operators.state import load_of


def candidates(best: DataFrame) -> DataFrame:
    """Vertices whose best label is strictly better than the current one."""
    return best.where(F.col("best") != F.col("cur"))


def candidate_loads(cands: DataFrame, unit: str = "degree") -> DataFrame:
    """(label, m, n, dmin, dmax, sum_deg2) of the candidates for each label."""
    load = load_of(unit)
    return cands.groupBy(F.col("best").alias("label")).agg(
        F.sum(load).alias("m"), F.count(F.lit(1)).alias("n"), F.min(load).alias("dmin"), F.max(load).alias("dmax"), F.sum(load * load).alias("sum_deg2")
    )


def migration_probability(r: float, m: float, throttle: str = "probabilistic") -> float:
    if throttle == "none":
        return 1.0
    return min(1.0, max(0.0, r / m)) if m else 0.0


def migration_probabilities(loads: DataFrame, m: DataFrame, cap: float) -> DataFrame:
    """(label, r, m, p) as a frame of k rows."""
    r = F.lit(float(cap)) - F.coalesce("b", F.lit(0)).cast("double")
    return m.select("label", "m").join(loads.select("label", "b"), "label", "left").select("label", r.alias("r"), "m", F.least(F.lit(1.0), F.greatest(F.lit(0.0), r / F.col("m").cast("double"))).alias("p"))


def migrate(best: DataFrame, p: dict[int, float], seed: int, t: int, provider: str = "fast") -> DataFrame:
    """(v, cur, new): new differs from cur for the candidates whose draw is under their label's probability."""
    table = F.create_map(*(x for k, v in sorted(p.items()) for x in (F.lit(k), F.lit(float(v))))) if p else None
    chance = F.coalesce(F.try_element_at(table, F.col("best")), F.lit(0.0)) if table is not None else F.lit(0.0)
    go = (F.col("best") != F.col("cur")) & (draw(provider, seed, t, "mig", "v") / F.lit(RANGE) < chance)
    return best.withColumn("new", F.when(go, F.col("best")).otherwise(F.col("cur")).cast("int"))
