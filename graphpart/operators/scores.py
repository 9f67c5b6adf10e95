"""Neighbour histograms, scores, best labels.

A histogram (v, label, h, n) holds the weight and the number of a vertex's arcs to neighbours of each label. It is made by
pushing labels along arcs (one exchange, reduced before it), and kept up by the arcs of movers alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.functions.draws import draw


#: arcs of one vertex that one task holds at most
HUB = 1_000_000


def lay_out(arcs: DataFrame, verts: DataFrame, most: int, hub: int = HUB) -> DataFrame:
    """Arcs dealt once by their source, so that no iteration exchanges them again; the arcs of a hub lie in several parts.

    ``most`` is the largest degree. With hubs, arcs carry ``part``; what a hub tells goes to each of its parts.
    """
    n = int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if most <= hub:
        return arcs.repartition(n, "src")
    parts = verts.where(F.col("deg") > hub).select(F.col("v").alias("src"), F.ceil(F.col("deg") / F.lit(hub)).alias("parts"))
    part = F.coalesce(F.pmod(F.xxhash64("dst"), F.col("parts")), F.lit(0)).cast("int")
    return arcs.join(parts, "src", "left").select("src", "dst", "w", part.alias("part")).repartition(n, "src", "part")


def _along(told: DataFrame, arcs: DataFrame, hub: int = HUB) -> DataFrame:
    """What vertices (v, deg, ...) tell, on each of their arcs."""
    told = told.withColumnRenamed("v", "src")
    if "part" not in arcs.columns:
        return arcs.join(told.drop("deg"), "src")
    last = F.greatest(F.ceil(F.col("deg") / F.lit(hub)), F.lit(1)) - 1
    return arcs.join(told.withColumn("part", F.explode(F.sequence(F.lit(0), last.cast("int")))).drop("deg"), ["src", "part"])


def build_hist(arcs: DataFrame, labels: DataFrame, hub: int = HUB) -> DataFrame:
    pushed = _along(labels.select("v", "label", *(["deg"] if "part" in arcs.columns else [])), arcs, hub)
    return pushed.groupBy(F.col("dst").alias("v"), "label").agg(F.sum("w").alias("h"), F.count(F.lit(1)).alias("n"))


def hist_delta(arcs: DataFrame, moves: DataFrame, hub: int = HUB) -> DataFrame:
    """What movers (v, old, new; deg where arcs lie in parts) change in their neighbours' histograms."""
    told = _along(moves.select("v", "old", "new", *(["deg"] if "part" in arcs.columns else [])), arcs, hub)
    rows = told.select(F.col("dst").alias("v"), F.inline(F.array(F.struct(F.col("old").alias("label"), (-F.col("w")).alias("h"), F.lit(-1).alias("n")), F.struct(F.col("new").alias("label"), F.col("w").alias("h"), F.lit(1).alias("n")))))
    return rows.groupBy("v", "label").agg(F.sum("h").alias("h"), F.sum("n").alias("n")).where("n <> 0 OR h <> 0")


def apply_delta(hist: DataFrame, delta: DataFrame) -> DataFrame:
    """The histogram after a delta; rows that reach zero go."""
    d = delta.withColumnsRenamed({"h": "dh", "n": "dn"})
    both = hist.join(d, ["v", "label"], "full_outer")
    return both.select("v", "label", (F.coalesce("h", F.lit(0)) + F.coalesce("dh", F.lit(0))).alias("h"), (F.coalesce("n", F.lit(0)) + F.coalesce("dn", F.lit(0))).alias("n")).where("n > 0")


def score_count(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """(v, label, score): neighbours that have the label."""
    return build_hist(arcs, labels).select("v", "label", F.col("n").alias("score"))


def score_weighted(arcs: DataFrame, labels: DataFrame) -> DataFrame:
    """(v, label, score): weight of arcs to neighbours that have the label."""
    return build_hist(arcs, labels).select("v", "label", F.col("h").alias("score"))


def _balanced(h, w, b, cap: float):
    return h.cast("double") / w.cast("double") - b.cast("double") / F.lit(float(cap))


def score_balanced(hist: DataFrame, state: DataFrame, loads: DataFrame, cap: float, candidates: str = "compact") -> DataFrame:
    """(v, label, score, is_current, deg, cur) for the labels a vertex chooses from.

    all_k: every label. compact: labels of neighbours, the current one, and the least loaded ones; a label that no
    neighbour has scores its fill alone, so none of the others can win and the result is the same.
    """
    b = F.broadcast(loads.select("label", "b"))  # k rows
    alive = state.where("wdeg > 0").select("v", F.col("label").alias("cur"), "deg", "wdeg")
    if candidates == "all_k":
        grid = alive.join(b)
        rows = grid.join(hist.select("v", "label", "h"), ["v", "label"], "left")
        out = rows.select("v", "cur", "deg", "wdeg", "label", "b", F.coalesce("h", F.lit(0)).alias("h"))
    elif candidates == "compact":
        least = loads.agg(F.min("b")).first()[0]
        idle = F.broadcast(loads.where(F.col("b") == F.lit(least)).select("label"))
        seen = hist.select("v", "label", "h")
        zero = F.lit(0).cast("long").alias("h")
        extra = alive.select("v", F.col("cur").alias("label"), zero).union(alive.select("v").join(idle).select("v", "label", zero))
        pool = seen.union(extra).groupBy("v", "label").agg(F.max("h").alias("h"))
        out = pool.join(b, "label").join(alive, "v")
    else:
        raise ValueError("candidates is compact or all_k")
    return out.select("v", "label", _balanced(F.col("h"), F.col("wdeg"), F.col("b"), cap).alias("score"), (F.col("label") == F.col("cur")).cast("int").alias("is_current"), "deg", "cur", "h", "wdeg")


def best_label(scores: DataFrame, seed: int, t: int, provider: str = "fast") -> DataFrame:
    """(v, cur, best, deg, s_cur, s_best): the current label if it is among the best, otherwise a draw among them."""
    tie = draw(provider, seed, t, "tie", "v", "label")
    key = F.struct("score", "is_current", tie.alias("tie"), "label")
    best = scores.groupBy("v").agg(
        F.max(key).alias("b"), F.max("cur").alias("cur"), F.max("deg").alias("deg"), F.max(F.when(F.col("is_current") == 1, F.col("score"))).alias("s_cur")
    )
    return best.select("v", "cur", F.col("b.label").alias("best"), "deg", "s_cur", F.col("b.score").alias("s_best"))


def graph_score(hist: DataFrame, state: DataFrame, loads: DataFrame, cap: float) -> DataFrame:
    """One row: the sum of all vertices' scores for their current labels."""
    alive = state.where("wdeg > 0").join(hist.select("v", "label", "h"), ["v", "label"], "left").join(F.broadcast(loads.select("label", "b")), "label")
    return alive.agg(F.sum(_balanced(F.coalesce("h", F.lit(0)), F.col("wdeg"), F.col("b"), cap)).alias("score"))
