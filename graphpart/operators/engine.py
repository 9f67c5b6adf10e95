"""Balanced label propagation end to end: two jobs an iteration, k rows to the driver, lineage cut in the shared folder."""

from __future__ import annotations

import pickle
import time
import warnings
from dataclasses import dataclass, field
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphpart.operators import convert, local, migrate, scores
from graphpart.operators import state as st
from graphpart.session import durable, durable_as_dealt, release


@dataclass
class SteadyState:
    """Halt once the gain of the score has been at most ``eps`` for more than ``patience`` iterations in a row.

    mode: per_vertex (gain divided by vertices), absolute, relative (to the score before).
    """

    eps: float = 0.001
    patience: int = 5
    mode: str = "per_vertex"
    stagnant: int = 0
    before: float | None = None

    def __call__(self, score: float, n: int, moved: int | None) -> bool:
        if self.before is not None:
            gain = score - self.before
            gain = gain / max(1, n) if self.mode == "per_vertex" else gain / max(1e-12, abs(self.before)) if self.mode == "relative" else gain
            self.stagnant = self.stagnant + 1 if gain <= self.eps else 0
        self.before = score
        return self.stagnant > self.patience


@dataclass
class NoChange:
    """Halt when no vertex moved in the last iteration."""

    def __call__(self, score: float, n: int, moved: int | None) -> bool:
        return moved == 0


@dataclass
class FixedIterations:
    """Run ``n`` iterations; note where a steady state would have halted."""

    n: int
    record_halt: bool = False
    steady: SteadyState = field(default_factory=SteadyState)
    halted_at: int | None = None
    seen: int = 0

    def __call__(self, score: float, n: int, moved: int | None) -> bool:
        if self.record_halt and self.steady(score, n, moved) and self.halted_at is None:
            self.halted_at = self.seen
        self.seen += 1
        return self.seen > self.n


@dataclass
class PartitionResult:
    labels: DataFrame
    history: list[dict]
    k: int
    capacity: float
    label_set: list[int]
    vertices: DataFrame
    flows: list[dict] = field(default_factory=list)
    halted_at: int | None = None
    loads: list[dict[int, int]] = field(default_factory=list)
    bounds: list[dict] = field(default_factory=list)

    @property
    def iterations(self) -> int:
        return self.history[-1]["t"]

    @property
    def messages(self) -> int:
        return sum(h["messages"] for h in self.history)

    def history_frame(self, spark: SparkSession) -> DataFrame:
        schema = "t int, phi double, rho double, score double, candidates long, migrated long, messages long, compute_s double, migrate_s double"
        names = [c.split()[0] for c in schema.split(", ")]
        return spark.createDataFrame([tuple(h[n] for n in names) for h in self.history], schema)

    def flows_frame(self, spark: SparkSession) -> DataFrame:
        schema = "t int, from_label int, to_label int, load long"
        return spark.createDataFrame([(f["t"], f["from_label"], f["to_label"], f["load"]) for f in self.flows], schema)

    def loads_frame(self, spark: SparkSession) -> DataFrame:
        """(t, label, b): the load of each label before iteration t + 1."""
        return spark.createDataFrame([(t, i, int(b)) for t, row in enumerate(self.loads) for i, b in sorted(row.items())], "t int, label int, b long")

    def bounds_frame(self, spark: SparkSession) -> DataFrame:
        """(t, label, r, n, dmin, dmax, sum_deg2): free capacity and candidates of each label that was asked for; with record_flows."""
        names = ("t", "label", "r", "n", "dmin", "dmax", "sum_deg2")
        return spark.createDataFrame([tuple(x[n] for n in names) for x in self.bounds], "t int, label int, r double, n long, dmin long, dmax long, sum_deg2 long")

    def register_views(self, spark: SparkSession, prefix: str = "blp") -> None:
        self.labels.createOrReplaceTempView(f"{prefix}_labels")
        st.partition_loads(self.labels.join(self.vertices, "v")).createOrReplaceTempView(f"{prefix}_loads")
        self.history_frame(spark).createOrReplaceTempView(f"{prefix}_history")


def partition(
    edges: DataFrame,
    k: int,
    c: float = 1.05,
    eps: float = 0.001,
    patience: int = 5,
    directed: bool = True,
    seed: int = 42,
    max_iter: int = 200,
    *,
    weights: str = "reciprocal",
    unit: str = "degree",
    provider: str = "fast",
    candidate_set: str = "compact",
    throttle: str = "probabilistic",
    hist_mode: str = "delta",
    async_mode: str = "none",
    batches: int = 4,
    async_update: str = "target",
    eps_mode: str = "per_vertex",
    halting: Callable | None = None,
    vertices: DataFrame | None = None,
    record_flows: bool = False,
    capacity_weights: dict[int, float] | None = None,
    penalised: bool = True,
    most_local: int = local.MOST_ARCS,
) -> PartitionResult:
    """Partition a graph's vertices into k labels of about even load with many edges inside a label.

    capacity_weights gives labels uneven shares of the load; penalised=False leaves the fill out of the score.
    """
    arcs = durable(convert.to_weighted_undirected(edges, directed, weights))
    verts = convert.vertex_stats(arcs, vertices)
    if unit == "out_degree":
        verts = convert.out_degrees(edges, verts) if directed else verts.withColumn("odeg", F.col("deg"))
    verts = durable(verts)
    labels = st.init_random(verts, k, seed, provider)
    return run_loop(
        arcs, verts, labels, list(range(k)), c=c, seed=seed, max_iter=max_iter, unit=unit, provider=provider, candidate_set=candidate_set, throttle=throttle, hist_mode=hist_mode,
        async_mode=async_mode, batches=batches, async_update=async_update, halting=halting or SteadyState(eps, patience, eps_mode), record_flows=record_flows, capacity_weights=capacity_weights, penalised=penalised, most_local=most_local,
    )


def run_loop(
    arcs: DataFrame,
    verts: DataFrame,
    labels: DataFrame,
    label_set: list[int],
    *,
    c: float = 1.05,
    seed: int = 42,
    max_iter: int = 200,
    unit: str = "degree",
    provider: str = "fast",
    candidate_set: str = "compact",
    throttle: str = "probabilistic",
    hist_mode: str = "delta",
    async_mode: str = "none",
    batches: int = 4,
    async_update: str = "target",
    halting: Callable | None = None,
    active: DataFrame | None = None,
    record_flows: bool = False,
    capacity_weights: dict[int, float] | None = None,
    penalised: bool = True,
    hub: int = scores.HUB,
    most_local: int = local.MOST_ARCS,
) -> PartitionResult:
    """The loop from given labels. ``active`` (v) restricts who may move; neighbours of movers join it.

    A graph of at most ``most_local`` arcs runs in one task with the same labels (fast draws, synchronous, no record of flows).

    Files of histograms and states that no later iteration reads are deleted on the way.
    """
    spark = arcs.sparkSession
    halting = halting or SteadyState()
    k = len(label_set)
    if (capacity_weights or not penalised or unit == "out_degree") and async_mode in ("per_task", "sequential"):
        raise ValueError("uneven capacities, out-degrees and scores without penalty need async_mode none or batched")
    if active is not None and async_mode == "sequential":
        raise ValueError("the sequential mode sweeps all vertices")
    stats = ["deg", "wdeg", *(["odeg"] if unit == "out_degree" else [])]
    state = durable(verts.join(labels, "v").select("v", "label", *stats))
    top = state.agg(F.sum(st.load_of(unit)).alias("total"), F.max(st.load_of(unit)).alias("most"), F.max("deg").alias("deg"), F.count(F.lit(1)).alias("n"), F.sum("deg").alias("arcs")).first()
    total, n_vertices, n_arcs = top["total"] or 0, top["n"], top["arcs"] or 0
    caps = st.capacities(total, label_set, c, capacity_weights)
    cap = max(caps.values())
    n_rows = arcs.count() if n_arcs <= most_local else n_arcs  # coarse graphs carry loads in place of degrees
    if max(n_rows, n_vertices) <= most_local and provider == "fast" and async_mode == "none" and hist_mode == "delta" and not record_flows:
        if total and top["most"] > cap:
            warnings.warn(f"the largest vertex ({top['most']}) exceeds the capacity ({cap:.1f}): no labelling can keep the balance", stacklevel=3)
        got = durable(local.run_local(arcs, state, label_set, caps, c=c, seed=seed, max_iter=max_iter, stat=st.UNITS[unit], throttle=throttle, halting=halting, active=active, weighted_caps=bool(capacity_weights), penalised=penalised))
        out = pickle.loads(got.where("out IS NOT NULL").first()["out"])
        return PartitionResult(got.where("label >= 0").select("v", "label"), out["history"], k, cap, label_set, verts, [], out["halted_at"], out["seen"], [])
    arcs = durable_as_dealt(scores.lay_out(arcs, verts, top["deg"] or 0, hub))
    if total and top["most"] > cap:
        warnings.warn(f"the largest vertex ({top['most']}) exceeds the capacity ({cap:.1f}): no labelling can keep the balance", stacklevel=3)
    history, flows, seen, asked_of, messages, migrated = [], [], [], [], 0, None
    hist = best = moves = None
    stale = []
    n_cand, migrate_s, t = 0, 0.0, 0
    while True:
        began = time.time()
        if hist is None or hist_mode == "rebuild":
            stale += [hist] if hist is not None else []
            hist = durable(scores.build_hist(arcs, state, hub))
        elif migrated:
            stale.append(hist)
            hist = durable(scores.apply_delta(hist, scores.hist_delta(arcs, moves, hub)))
        # the new histogram and state stand in files, so nothing can ask for the ones before
        while stale:
            release(stale.pop())
        # one job: loads, and arcs inside a label
        by_label = state.join(hist.select("v", "label", F.col("n").alias("inside")), ["v", "label"], "left").groupBy("label")
        rows = by_label.agg(F.sum(st.load_of(unit)).alias("b"), F.count(F.lit(1)).alias("n"), F.sum("inside").alias("inside")).collect()
        loads = {i: (0, 0) for i in label_set} | {r["label"]: (r["b"], r["n"]) for r in rows}
        inside = sum(r["inside"] or 0 for r in rows)
        seen.append({i: b for i, (b, _) in loads.items()})
        if capacity_weights or not penalised:
            # loads as they weigh in the score: in proportion to the label's own capacity, or not at all
            loads_df = spark.createDataFrame([(i, b * cap / caps[i] if penalised else 0.0, int(n)) for i, (b, n) in sorted(loads.items())], "label int, b double, n long")
        else:
            loads_df = spark.createDataFrame([(i, int(b), int(n)) for i, (b, n) in sorted(loads.items())], "label int, b long, n long")
        scored = scores.score_balanced(hist, state, loads_df, cap, candidate_set)
        if best is not None:
            best.unpersist()
        if async_mode == "per_task":
            from graphpart.operators.async_tasks import score_per_task

            best = score_per_task(scored, loads, cap, unit, seed, t + 1, async_update).persist()
        else:
            best = scores.best_label(scored, seed, t + 1, provider).persist()
        # one job: best labels, their score, and what asks for each label
        chosen = best
        if active is not None:
            chosen = best.join(active.withColumn("_on", F.lit(1)), "v", "left").withColumn("best", F.when(F.col("_on") == 1, F.col("best")).otherwise(F.col("cur"))).drop("_on")
        if unit in ("weighted_degree", "out_degree"):
            chosen = chosen.join(verts.select("v", st.UNITS[unit]), "v")
        asks = F.col("best") != F.col("cur")
        asked = {r["best"]: r for r in chosen.groupBy("best").agg(F.sum("s_cur").alias("s"), F.sum(F.when(asks, st.load_of(unit))).alias("m"), F.count_if(asks).alias("n")).collect()}
        score = sum(r["s"] or 0.0 for r in asked.values())
        most = max(b for b, _ in loads.values())
        fullest = max(b * c / caps[i] for i, (b, _) in loads.items()) if capacity_weights and total else most * k / total if total else 1.0
        history.append({
            "t": t, "phi": inside / n_arcs if n_arcs else 1.0, "rho": fullest, "score": score, "candidates": n_cand, "migrated": migrated or 0,
            "messages": messages, "compute_s": time.time() - began, "migrate_s": migrate_s, "max_load": most,
        })
        if halting(score, n_vertices, migrated) or t >= max_iter:
            break
        t += 1
        began = time.time()
        if record_flows:
            asked_of += [r.asDict() | {"t": t, "r": caps[r["label"]] - loads[r["label"]][0]} for r in migrate.candidate_loads(migrate.candidates(chosen), unit).collect()]
        if async_mode == "batched":
            new, n_cand = _batched(chosen, migrate.candidates(chosen), loads, caps, unit, seed, t, provider, throttle, batches)
        elif async_mode == "sequential":
            from graphpart.operators.async_tasks import sweep

            new = sweep(arcs, state, loads, cap, unit, n_arcs).persist()
            n_cand = new.where("asked").count()
        else:
            p = {i: migrate.migration_probability(caps[i] - loads[i][0], r["m"], throttle) for i, r in asked.items() if r["n"]}
            n_cand = sum(r["n"] for r in asked.values())
            new = migrate.migrate(chosen, p, seed, t, provider)
        if moves is not None:
            moves.unpersist()
        moves = new.where("new <> cur").select("v", F.col("cur").alias("old"), "new", "deg").persist()
        got = moves.agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("deg")).first()
        migrated, messages = got["n"], (got["deg"] or 0) + (n_arcs if t == 1 else 0)
        if record_flows:
            flows += [r.asDict() | {"t": t} for r in moves.groupBy(F.col("old").alias("from_label"), F.col("new").alias("to_label")).agg(F.sum("deg").alias("load")).collect()]
        if migrated:
            stale.append(state)
            state = durable(state.join(moves.select("v", "new"), "v", "left").select("v", F.coalesce("new", "label").alias("label"), *stats))
            if active is not None:
                near = arcs.join(moves.select(F.col("v").alias("src")), "src", "left_semi").select(F.col("dst").alias("v"))
                active = durable(active.union(near).distinct())
        migrate_s = time.time() - began
    for x in (best, moves):
        if x is not None:
            x.unpersist()
    release(hist)
    release(arcs)
    return PartitionResult(state.select("v", "label"), history, k, cap, label_set, verts, flows, getattr(halting, "halted_at", None), seen, asked_of)


def _batched(best, cands, loads, caps, unit, seed, t, provider, throttle, batches):
    """Hash batches inside an iteration: each batch's probabilities see the loads after the batches before."""
    load = st.load_of(unit)
    b = {i: x for i, (x, _) in loads.items()}
    n_cand, parts = 0, []
    for j in range(batches):
        part = cands.where(F.pmod(F.xxhash64("v", F.lit(t)), F.lit(batches)) == j)
        m = {r["label"]: r for r in migrate.candidate_loads(part, unit).collect()}
        n_cand += sum(r["n"] for r in m.values())
        p = {i: migrate.migration_probability(caps[i] - b[i], r["m"], throttle) for i, r in m.items()}
        new = migrate.migrate(part, p, seed, t, provider)
        for r in new.where("new <> cur").groupBy("cur", "new").agg(F.sum(load).alias("x")).collect():
            b[r["cur"]] -= r["x"]
            b[r["new"]] += r["x"]
        parts.append(new.select("v", "cur", "deg", "new"))
    out = parts[0]
    for x in parts[1:]:
        out = out.union(x)
    return out, n_cand
