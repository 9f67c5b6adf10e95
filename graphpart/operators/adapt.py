"""Graph change and change of k: restart from the old labelling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.functions.draws import RANGE, draw
from graphpart.operators import convert
from graphpart.operators import state as st
from graphpart.operators.engine import PartitionResult, SteadyState, run_loop
from graphpart.session import durable


def snapshot(edges: DataFrame, until) -> DataFrame:
    """Edges no later than ``until`` (by ts)."""
    return edges.where(F.col("ts") <= F.lit(until)).select("src", "dst").distinct()


def holdout(edges: DataFrame, fraction: float, seed: int = 42, provider: str = "fast") -> tuple[DataFrame, DataFrame]:
    """(kept, held out): each pair by a draw, whichever way it is written."""
    hit = draw(provider, seed, 0, "hold", F.least("src", "dst"), F.greatest("src", "dst")) / F.lit(RANGE) < F.lit(fraction)
    return edges.where(~hit), edges.where(hit)


def diff_edges(old: DataFrame, new: DataFrame) -> DataFrame:
    """(op, src, dst): what makes new of old."""
    a, b = old.select("src", "dst"), new.select("src", "dst")
    return b.subtract(a).select(F.lit("add").alias("op"), "src", "dst").union(a.subtract(b).select(F.lit("remove").alias("op"), "src", "dst"))


def apply_changes(edges: DataFrame, changes: DataFrame) -> DataFrame:
    """Edges after a list of changes (op, src, dst)."""
    gone = changes.where("op = 'remove'").select("src", "dst")
    return edges.select("src", "dst").join(gone, ["src", "dst"], "left_anti").union(changes.where("op = 'add'").select("src", "dst")).distinct()


def adapt_graph(
    labels: DataFrame, edges_new: DataFrame, k: int, *, scope: str = "all", edges_old: DataFrame | None = None, new_vertices: str = "least_loaded", directed: bool = True, weights: str = "reciprocal",
    seed: int = 43, provider: str = "fast", unit: str = "degree", halting=None, label_set: list[int] | None = None, **loop,
) -> PartitionResult:
    """Adapt a labelling to a changed graph. scope all: every vertex takes part; affected: the ends of changed edges and, from then on, neighbours of movers."""
    arcs = durable(convert.to_weighted_undirected(edges_new, directed, weights))
    verts = durable(convert.vertex_stats(arcs))
    ids = label_set or list(range(k))
    start = st.init_from(labels, verts, new_vertices, k, seed, provider, unit, ids)
    active = None
    if scope == "affected":
        if edges_old is None:
            raise ValueError("scope 'affected' needs edges_old")
        ends = diff_edges(convert.validate_edges(edges_old), convert.validate_edges(edges_new))
        active = durable(ends.select(F.col("src").alias("v")).union(ends.select(F.col("dst").alias("v"))).distinct())
    return run_loop(arcs, verts, start, ids, seed=seed, provider=provider, unit=unit, halting=halting or SteadyState(), active=active, **loop)


def reseed_k(labels: DataFrame, label_set: list[int], add: int = 0, remove: list[int] | None = None, seed: int = 42, provider: str = "fast") -> tuple[DataFrame, list[int]]:
    """Labels and label ids after removing, then adding labels; no iterations.

    Growth by n: a vertex moves with probability n/(k+n) to a uniformly drawn new label. Shrinking: members of the removed
    labels are dealt uniformly to the others. Labels that stay keep their ids.
    """
    ids = sorted(label_set)
    out = labels.select("v", "label")
    if remove:
        kept = [i for i in ids if i not in set(remove)]
        if not kept:
            raise ValueError("at least one label must stay")
        pick = F.element_at(F.array(*map(F.lit, kept)), F.pmod(draw(provider, seed, 0, "shrink", "v"), F.lit(len(kept))).cast("int") + 1)
        out = out.select("v", F.when(F.col("label").isin(list(remove)), pick).otherwise(F.col("label")).cast("int").alias("label"))
        ids = kept
    if add:
        fresh = [max(label_set) + 1 + i for i in range(add)]
        go = draw(provider, seed, 0, "grow", "v") / F.lit(RANGE) < F.lit(add / (len(ids) + add))
        pick = F.element_at(F.array(*map(F.lit, fresh)), F.pmod(draw(provider, seed, 0, "pick", "v"), F.lit(add)).cast("int") + 1)
        out = out.select("v", F.when(go, pick).otherwise(F.col("label")).cast("int").alias("label"))
        ids = ids + fresh
    return out, ids


def adapt_k(
    labels: DataFrame, edges: DataFrame, label_set: list[int], *, add: int = 0, remove: list[int] | None = None, directed: bool = True, weights: str = "reciprocal", seed: int = 43, provider: str = "fast", halting=None, **loop,
) -> PartitionResult:
    """Adapt a labelling to more or fewer labels."""
    arcs = durable(convert.to_weighted_undirected(edges, directed, weights))
    verts = durable(convert.vertex_stats(arcs))
    start, ids = reseed_k(labels, label_set, add, remove, seed, provider)
    return run_loop(arcs, verts, start, ids, seed=seed, provider=provider, halting=halting or SteadyState(), **loop)
