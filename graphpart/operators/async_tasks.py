"""Asynchrony inside a worker: each task keeps its own load counters and updates them as its vertices become candidates."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 16_384  # vertices a task holds before it hands them on
MOST_SEQUENTIAL = 2_000_000  # arcs of a graph that one task may sweep


def score_per_task(scored: DataFrame, loads: dict[int, tuple[int, int]], cap: float, unit: str, seed: int, t: int, update: str = "target") -> DataFrame:
    """(v, cur, best, deg, s_cur, s_best), like best_label, with loads that drift within a task as vertices choose.

    Vertices are dealt by id and taken in id order, so a given number of tasks gives the same result again.
    """
    n = int(scored.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = scored.select("v", "label", "h", "wdeg", "cur", "deg").repartition(n, "v").sortWithinPartitions("v", "label")
    ids = sorted(loads)
    at = {i: j for j, i in enumerate(ids)}
    start = np.array([float(loads[i][0]) for i in ids])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b = start.copy()
        stream = (r for batch in batches for r in zip(*(c.to_pylist() for c in batch.columns), strict=True))
        types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.float64())

        def block() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(out, types, strict=True)], names=["v", "cur", "best", "deg", "s_cur", "s_best"])

        out: list[list] = [[] for _ in range(6)]
        for v, group in groupby(stream, key=lambda r: r[0]):
            options = list(group)
            cur, deg = options[0][4], options[0][5]
            rng = np.random.default_rng((seed, t, v & 0xFFFFFFFF))
            key = [(h / w - b[at[label]] / cap, label == cur, rng.random(), label) for _, label, h, w, _, _ in options]
            s, _, _, best = max(key)
            s_cur = next(x[0] for x in key if x[3] == cur)
            if best != cur:
                load = 1 if unit == "vertices" else options[0][3] if unit == "weighted_degree" else deg
                b[at[best]] += load
                if update == "both":
                    b[at[cur]] -= load
            for col, x in zip(out, (v, cur, best, deg, s_cur, s), strict=True):
                col.append(x)
            if len(out[0]) == BLOCK:
                yield block()
                out = [[] for _ in range(6)]
        yield block()

    return rows.mapInArrow(run, "v long, cur int, best int, deg long, s_cur double, s_best double")


def sweep(arcs: DataFrame, state: DataFrame, loads: dict[int, tuple[int, int]], cap: float, unit: str, n_arcs: int) -> DataFrame:
    """(v, cur, new, deg, asked): one pass over all vertices in id order in one task; a move is seen by all that follow.

    A vertex takes its best label (the current one first among equals, then the smallest) if the label still has room for
    it. The order is total, so this can't be dealt out: graphs over MOST_SEQUENTIAL arcs are refused.
    """
    if n_arcs > MOST_SEQUENTIAL:
        raise ValueError(f"the sequential mode takes at most {MOST_SEQUENTIAL} arcs, not {n_arcs}")
    near = arcs.groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("dst"), F.collect_list("w").alias("w"))
    rows = state.join(near, "v").select("v", "label", "deg", "wdeg", "dst", "w").coalesce(1).sortWithinPartitions("v")
    start = {i: float(b) for i, (b, _) in loads.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = [r for batch in batches for r in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
        label, b = {r[0]: r[1] for r in graph}, dict(start)
        out: list[list] = [[] for _ in range(5)]
        for v, cur, deg, wdeg, dst, w in graph:
            h = dict.fromkeys(b, 0)
            for u, x in zip(dst, w, strict=True):
                h[label[u]] += x
            best = max(h, key=lambda i: (h[i] / wdeg - b[i] / cap, i == cur, -i))
            load = 1 if unit == "vertices" else wdeg if unit == "weighted_degree" else deg
            go = best != cur and b[best] + load <= cap
            if go:
                b[cur], b[best], label[v] = b[cur] - load, b[best] + load, best
            for col, x in zip(out, (v, cur, best if go else cur, deg, best != cur), strict=True):
                col.append(x)
        types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.bool_())
        yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(out, types, strict=True)], names=["v", "cur", "new", "deg", "asked"])

    return rows.mapInArrow(run, "v long, cur int, new int, deg long, asked boolean")
