"""Edge hygiene and conversion of directed input to a weighted, undirected graph of arcs (two rows a pair)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def validate_edges(edges: DataFrame) -> DataFrame:
    """(src, dst) without nulls, loops and repeats."""
    missing = {"src", "dst"} - set(edges.columns)
    if missing:
        raise ValueError(f"edges lack {sorted(missing)}")
    rows = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
    return rows.where("src IS NOT NULL AND dst IS NOT NULL AND src <> dst").distinct()


def _both_ways(edges: DataFrame) -> DataFrame:
    """Each row in both directions, from one scan; ``side`` is 1 as written and 2 turned round. Rows with nulls and loops go."""
    missing = {"src", "dst"} - set(edges.columns)
    if missing:
        raise ValueError(f"edges lack {sorted(missing)}")
    s, d = F.col("src").cast("long"), F.col("dst").cast("long")
    pair = lambda a, b, side: F.struct(a.alias("src"), b.alias("dst"), F.lit(side).alias("side"))
    return edges.where(s.isNotNull() & d.isNotNull() & (s != d)).select(F.inline(F.array(pair(s, d, 1), pair(d, s, 2))))


def to_weighted_undirected(edges: DataFrame, directed: bool = True, weights: str = "reciprocal") -> DataFrame:
    """Arcs (src, dst, w): a pair weighs 2 where both directions exist and 1 otherwise.

    ``weights``: reciprocal; naive (always 1); multiplicity (parallel edges are counted). Undirected input weighs 1.
    """
    if weights == "multiplicity":
        return _both_ways(edges).groupBy("src", "dst").agg(F.count(F.lit(1)).cast("int").alias("w"))
    if weights == "naive" or not directed:
        return to_undirected(edges)
    # which directions were seen, as bits: repeats vanish in the same exchange that pairs the directions
    return _both_ways(edges).groupBy("src", "dst").agg(F.bit_count(F.bit_or("side")).cast("int").alias("w"))


def to_undirected(edges: DataFrame) -> DataFrame:
    """Arcs of weight 1 whatever the directions."""
    return _both_ways(edges).select("src", "dst").distinct().withColumn("w", F.lit(1))


def convert_with_cost(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Conversion as two rounds of messages: every vertex tells its id along its out-edges; who knows the sender raises the weight, who doesn't makes the edge.

    Returns the arcs and one row: messages sent, edges raised, edges created.
    """
    e = validate_edges(edges)
    told = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("told"))
    met = e.withColumn("own", F.lit(1)).join(told, ["src", "dst"], "full_outer")
    arcs = met.select("src", "dst", (F.coalesce("own", F.lit(0)) + F.coalesce("told", F.lit(0))).alias("w"))
    cost = met.agg(
        F.count("told").alias("messages"),
        F.count_if(F.col("own").isNotNull() & F.col("told").isNotNull()).alias("raised"),
        F.count_if(F.col("own").isNull()).alias("created"),
    )
    return arcs, cost


def reciprocity(edges: DataFrame) -> DataFrame:
    """One row: edges, and those whose reverse exists."""
    e = validate_edges(edges)
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return e.agg(F.count(F.lit(1)).alias("edges")).crossJoin(e.intersect(back).agg(F.count(F.lit(1)).alias("reciprocal")))


def vertex_stats(arcs: DataFrame, ids: DataFrame | None = None) -> DataFrame:
    """(v, deg, wdeg); with ``ids`` (v), isolated vertices too."""
    stats = arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"), F.sum("w").alias("wdeg"))
    if ids is None:
        return stats
    return ids.select("v").distinct().join(stats, "v", "left").select("v", F.coalesce("deg", F.lit(0)).alias("deg"), F.coalesce("wdeg", F.lit(0)).alias("wdeg"))


def out_degrees(edges: DataFrame, verts: DataFrame) -> DataFrame:
    """Vertices with ``odeg``, the out-edges as the input writes them."""
    out = validate_edges(edges).groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("odeg"))
    return verts.join(out, "v", "left").withColumn("odeg", F.coalesce("odeg", F.lit(0)))


def degree_stats(arcs: DataFrame) -> DataFrame:
    """One row: arcs, vertices, least, mean, largest degree."""
    return vertex_stats(arcs).agg(
        F.sum("deg").alias("arcs"), F.count(F.lit(1)).alias("vertices"), F.min("deg").alias("min_deg"), F.round(F.avg("deg"), 6).alias("mean_deg"), F.max("deg").alias("max_deg")
    )


def feasible_k(arcs: DataFrame, c: float = 1.05) -> DataFrame:
    """One row: the largest k whose capacity holds the largest vertex."""
    return vertex_stats(arcs).agg(F.floor(F.lit(c) * F.sum("deg") / F.max("deg")).alias("k_max"))
