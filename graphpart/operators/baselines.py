"""What the method is compared with: hash, random, chunks, plain propagation, one-pass streaming, multilevel, coarsening by propagation, central relocation.

The one-pass and multilevel cores are sequential by nature. They run in one task behind a checked size
limit; the streaming ones also run in mini-batches at any size.
"""

from __future__ import annotations

import heapq
import math
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.functions.draws import draw
from graphpart.operators import convert, migrate, scores
from graphpart.operators import state as st
from graphpart.operators.engine import NoChange
from graphpart.session import durable, ship

MOST_SEQUENTIAL = 5_000_000  # arcs that one task may hold (160 MB)
MOST_COARSE = 200_000  # coarse arcs that one task's Python holds as dicts


def hash_partition(vertices: DataFrame, k: int, flavour: str = "modulo") -> DataFrame:
    """v mod k, or a mixed hash mod k."""
    h = F.col("v") if flavour == "modulo" else F.xxhash64("v")
    return vertices.select("v", F.pmod(h, F.lit(k)).cast("int").alias("label"))


def random_partition(vertices: DataFrame, k: int, seed: int = 42, provider: str = "fast") -> DataFrame:
    return st.init_random(vertices, k, seed, provider)


def chunk_partition(vertices: DataFrame, k: int) -> DataFrame:
    """Consecutive blocks of ids: bounds from exact quantiles by a two-step count, no global sort in one task."""
    n = vertices.count()
    size = -(-n // k) if n else 1
    top = vertices.agg(F.min("v").alias("lo"), F.max("v").alias("hi")).first()
    if not n:
        return vertices.select("v", F.lit(0).alias("label"))
    width = max(1, (top["hi"] - top["lo"] + 1024) // 1024)
    part = F.floor((F.col("v") - F.lit(top["lo"])) / width).cast("int")
    counts = {r["part"]: r["n"] for r in vertices.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).collect()}
    before, at = [], 0
    for p in range(max(counts) + 1):
        before.append(at)
        at += counts.get(p, 0)
    from pyspark.sql import Window

    rank = F.row_number().over(Window.partitionBy("part").orderBy("v")) - 1 + F.element_at(F.lit(before), F.col("part") + 1)
    return vertices.select("v", part.alias("part")).select("v", F.floor(rank / F.lit(size)).cast("int").alias("label"))


def plain_lpa(edges: DataFrame, k: int, weighted: bool = True, directed: bool = True, seed: int = 42, provider: str = "fast", max_iter: int = 30, halting=None) -> tuple[DataFrame, list[dict]]:
    """Label propagation without balance: synchronous, ties keep the current label, else a draw. May swap for ever on bipartite graphs."""
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    verts = convert.vertex_stats(arcs)
    labels, history, halting = durable(st.init_random(verts, k, seed, provider)), [], halting or NoChange()
    n = labels.count()
    for t in range(1, max_iter + 1):
        h = scores.build_hist(arcs, labels)
        s = h.select("v", "label", F.col("h" if weighted else "n").alias("score")).join(labels.withColumnRenamed("label", "cur"), "v")
        s = s.withColumn("is_current", (F.col("label") == F.col("cur")).cast("int")).withColumn("deg", F.lit(0))
        best = durable(scores.best_label(s, seed, t, provider))
        moved = best.where("best <> cur").count()
        history.append({"t": t, "migrated": moved})
        labels = durable(labels.join(best.select("v", "best"), "v", "left").select("v", F.coalesce("best", "label").cast("int").alias("label")))
        if halting(0.0, n, moved):
            break
    return labels, history


# -- one pass


def _adjacency_order(arcs: DataFrame, order: str, seed: int) -> DataFrame:
    """(v, pos): the order of arrival."""
    ids = arcs.select(F.col("src").alias("v")).distinct()
    if order == "natural":
        return ids.select("v", F.col("v").alias("pos"))
    if order == "random":
        return ids.select("v", draw("portable", seed, 0, "order", "v").alias("pos"))
    raise ValueError("order is natural or random; bfs is made inside the sequential core")


def _one_pass(arcs: DataFrame, k: int, order: str, seed: int, choose) -> DataFrame:
    n = arcs.count()
    if n > MOST_SEQUENTIAL:
        raise ValueError(f"{n} arcs are too many for the sequential core; use batches")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        src, dst, pos = (np.concatenate([b.column(i).to_numpy() for b in cols] or [np.zeros(0, np.int64)]) for cols in [list(batches)] for i in range(3))
        near: dict[int, list[int]] = defaultdict(list)
        for a, b in zip(src.tolist(), dst.tolist(), strict=True):
            near[a].append(b)
        first = dict(zip(src.tolist(), pos.tolist(), strict=True))
        ids = sorted(near, key=lambda v: (first[v], v))
        if order == "bfs":
            seen, queue, out = set(), [], []
            for root in ids:
                if root in seen:
                    continue
                seen.add(root)
                queue = [root]
                for v in queue:
                    for u in sorted(near[v]):
                        if u not in seen:
                            seen.add(u)
                            queue.append(u)
                out += queue
            ids = out
        label: dict[int, int] = {}
        size, load = [0] * k, [0] * k
        for v in ids:
            have = [0] * k
            for u in near[v]:
                if u in label:
                    have[label[u]] += 1
            label[v] = j = choose(have, size, load, len(near[v]))
            size[j] += 1
            load[j] += len(near[v])
        yield pa.RecordBatch.from_arrays([pa.array(list(label), pa.int64()), pa.array(list(label.values()), pa.int32())], names=["v", "label"])

    placed = arcs.join(_adjacency_order(arcs, "natural" if order == "bfs" else order, seed).withColumnRenamed("v", "src"), "src").select("src", "dst", F.col("pos").cast("long").alias("pos"))
    return placed.coalesce(1).mapInArrow(run, "v long, label int")


def stream_greedy(edges: DataFrame, k: int, order: str = "random", weight: str = "linear", slack: float = 1.05, unit: str = "degree", directed: bool = True, seed: int = 42, batches: int | None = None) -> DataFrame:
    """One pass; a vertex goes where most of its neighbours are, times the room left (linear), unweighted (none), or exponential.

    weight 'balanced' ignores neighbours. With ``batches``, the pass is cut into mini-batches that see earlier assignments only.
    """
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    if batches:
        return _mini_batches(arcs, k, batches, seed, slack, unit, lambda h, load, cap: h * (1 - load / F.lit(cap)))
    top = convert.vertex_stats(arcs).agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("m")).first()
    cap = slack * ((top["m"] or 0) if unit == "degree" else top["n"]) / k

    def choose(have, size, load, deg):
        full = load if unit == "degree" else size
        open_ = [i for i in range(k) if full[i] < cap] or list(range(k))
        factor = {"linear": lambda x: 1 - x / cap, "none": lambda x: 1.0, "exponential": lambda x: 1 - math.exp(min(0.0, x - cap)), "balanced": lambda x: 0.0}[weight]
        return max(open_, key=lambda i: (have[i] * factor(full[i]), -full[i], -i))

    return _one_pass(arcs, k, order, seed, choose)


def stream_interpolated(edges: DataFrame, k: int, gamma: float = 1.5, nu: float = 1.1, alpha: float | None = None, order: str = "random", unit: str = "degree", directed: bool = True, seed: int = 42, batches: int | None = None) -> DataFrame:
    """One pass; neighbours minus the marginal cost alpha * gamma * size^(gamma - 1), labels at nu times the even size closed."""
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    top = convert.vertex_stats(arcs).agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("m")).first()
    n = float((top["m"] if unit == "degree" else top["n"]) or 1)
    m = float(top["m"] or 0) / 2
    a = alpha if alpha is not None else m * k ** (gamma - 1) / n**gamma
    cap = nu * n / k
    if batches:
        return _mini_batches(arcs, k, batches, seed, nu, unit, lambda h, load, cap: h - F.lit(a * gamma) * F.pow(load, F.lit(gamma - 1)))

    def choose(have, size, load, deg):
        full = load if unit == "degree" else size
        room = [i for i in range(k) if full[i] + (deg if unit == "degree" else 1) <= cap] or [min(range(k), key=lambda i: (full[i], i))]
        return max(room, key=lambda i: (have[i] - a * gamma * full[i] ** (gamma - 1), -full[i], -i))

    return _one_pass(arcs, k, order, seed, choose)


def _mini_batches(arcs: DataFrame, k: int, batches: int, seed: int, slack: float, unit: str, value) -> DataFrame:
    """The pass in mini-batches: labels up to the last batch are joined, k loads broadcast, inflow throttled to the room left; who finds none goes to the least loaded."""
    spark = arcs.sparkSession
    verts = durable(convert.vertex_stats(arcs).withColumn("batch", F.pmod(draw("fast", seed, 0, "batch", "v"), F.lit(batches))))
    load = st.load_of(unit)
    total = verts.agg(F.sum(load)).first()[0] or 0
    cap = slack * total / k
    loads = dict.fromkeys(range(k), 0)
    done = spark.createDataFrame([], "v long, label int")
    for j in range(batches):
        mine = verts.where(F.col("batch") == j)
        h = arcs.join(done.select(F.col("v").alias("dst"), "label"), "dst").join(mine.select(F.col("v").alias("src")), "src", "left_semi").groupBy(F.col("src").alias("v"), "label").agg(F.count(F.lit(1)).alias("h"))
        room = spark.createDataFrame([(i, float(x)) for i, x in loads.items() if x < cap] or [(0, 0.0)], "label int, x double")
        s = h.join(F.broadcast(room), "label").select("v", F.struct(value(F.col("h"), F.col("x"), cap).alias("s"), (-F.col("x")).alias("x"), (-F.col("label")).alias("l")).alias("k"))
        want = mine.join(s.groupBy("v").agg((-F.max("k")["l"]).alias("want")), "v", "left").withColumn("cost", load)
        m = {r["want"]: r["m"] for r in want.groupBy("want").agg(F.sum("cost").alias("m")).collect()}
        p = {i: min(1.0, max(0.0, (cap - loads[i]) / x)) if x else 1.0 for i, x in m.items() if i is not None}
        table = F.create_map(*(y for i, x in p.items() for y in (F.lit(i), F.lit(float(x))))) if p else None
        go = F.col("want").isNotNull() & (draw("fast", seed, j, "go", "v") / F.lit(4294967296.0) < F.coalesce(F.try_element_at(table, F.col("want")), F.lit(0.0))) if table is not None else F.lit(False)
        # the others are dealt over labels by the room left
        free = [max(0.0, cap - loads[i]) for i in range(k)]
        whole = sum(free) or 1.0
        at, place, u = 0.0, F.lit(k - 1), draw("fast", seed, j, "deal", "v") / F.lit(4294967296.0)
        cuts = []
        for i in range(k):
            at += free[i] / whole
            cuts.append((i, at))
        for i, cut in reversed(cuts):
            place = F.when(u < F.lit(cut), F.lit(i)).otherwise(place)
        put = durable(want.select("v", F.when(go, F.col("want")).otherwise(place).cast("int").alias("label"), "cost"))
        for r in put.groupBy("label").agg(F.sum("cost").alias("x")).collect():
            loads[r["label"]] += r["x"]
        done = durable(done.union(put.select("v", "label")))
    return done


# -- multilevel


def _match(nodes: DataFrame, arcs: DataFrame, seed: int, level: int) -> DataFrame:
    """(v, up): mutual proposals of the heaviest neighbour merge; up is the smaller id."""
    tie = draw("portable", seed, level, "match", F.least("src", "dst"), F.greatest("src", "dst"))
    pick = arcs.groupBy("src").agg(F.max(F.struct("w", tie.alias("tie"), "dst")).alias("b")).select(F.col("src").alias("v"), F.col("b.dst").alias("to"))
    back = pick.select(F.col("v").alias("to"), F.col("to").alias("back"))
    return nodes.select("v").join(pick.join(back, "to", "left").select("v", F.when(F.col("back") == F.col("v"), F.least("v", "to")).otherwise(F.col("v")).alias("up")), "v", "left").select("v", F.coalesce("up", "v").alias("up"))


def contract(nodes: DataFrame, arcs: DataFrame, up: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes (v, weight) and arcs (src, dst, w) after merging by (v, up)."""
    a = arcs.join(up.select(F.col("v").alias("src"), F.col("up").alias("a")), "src").join(up.select(F.col("v").alias("dst"), F.col("up").alias("b")), "dst")
    coarse = a.where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("w").alias("w"))
    return durable(nodes.join(up, "v").groupBy(F.col("up").alias("v")).agg(F.sum("weight").alias("weight"))), durable(coarse)


def _grow_and_refine(weight: dict[int, int], near: dict[int, dict[int, int]], k: int, limit: float, label: dict[int, int] | None = None, passes: int = 10) -> dict[int, int]:
    """Greedy growing from k seeds, then boundary moves of positive gain within the load limit."""
    load = [0.0] * k
    if label is None:
        label = {}
        order = sorted(weight, key=lambda v: (-sum(near[v].values()), v))
        goal = sum(weight.values()) / k
        free = dict.fromkeys(order)
        strength = {v: max(1, sum(near[v].values())) for v in weight}
        for j in range(k):
            gain: dict[int, float] = {}
            heap: list[tuple[float, float, int]] = []  # by gain over strength, gain, id; an entry counts while it tells the gain as it is
            while free and load[j] < goal and (j < k - 1 or free):
                while heap and gain.get(heap[0][2]) != -heap[0][1]:
                    heapq.heappop(heap)
                v = heapq.heappop(heap)[2] if gain else next(iter(free))
                gain.pop(v, None)
                if load[j] + weight[v] > limit and load[j]:
                    if not gain:
                        break
                    continue
                del free[v]
                label[v] = j
                load[j] += weight[v]
                for u, w in near[v].items():
                    if u in free:
                        gain[u] = gain.get(u, 0) + w
                        heapq.heappush(heap, (-gain[u] / strength[u], -gain[u], u))
        for v in free:
            j = min(range(k), key=lambda i: (load[i], i))
            label[v] = j
            load[j] += weight[v]
    else:
        for v, j in label.items():
            load[j] += weight[v]
    for _ in range(passes):
        moved = 0
        for v in sorted(weight, key=lambda x: (weight[x], x)):
            have: dict[int, int] = defaultdict(int)
            for u, w in near[v].items():
                have[label[u]] += w
            cur = label[v]
            options = [(have[j] - have.get(cur, 0), -load[j], -j) for j in have if j != cur and load[j] + weight[v] <= limit]
            if load[cur] > limit:
                options += [(have.get(j, 0) - have.get(cur, 0), -load[j], -j) for j in range(k) if j != cur and load[j] + weight[v] <= limit]
            if options and (max(options)[0] > 0 or load[cur] > limit):
                j = -max(options)[2]
                load[cur] -= weight[v]
                load[j] += weight[v]
                label[v] = j
                moved += 1
        if not moved:
            break
    return label


def _fits(nodes: DataFrame, arcs: DataFrame) -> bool:
    return max(arcs.count(), nodes.count()) <= MOST_COARSE


def _coarsest(nodes: DataFrame, arcs: DataFrame, k: int, imbalance: float, seed: int) -> DataFrame:
    """(v, label) of the coarsest graph: grown in one task, or, where coarsening stalled at a graph that doesn't fit there, by the throttled loop in Spark."""
    if _fits(nodes, arcs):
        return _in_one_task(nodes, arcs, k, imbalance)
    return _refine_in_spark(nodes, arcs, st.init_random(nodes, k, seed), k, imbalance, seed, passes=12)


def _in_one_task(nodes: DataFrame, arcs: DataFrame, k: int, imbalance: float, labels: DataFrame | None = None) -> DataFrame:
    """(v, label) grown from nothing, or refined from ``labels``. The graph stays out of the driver, whose Python would keep the memory."""
    ship(nodes.sparkSession)
    zero = F.lit(0).cast("long")
    rows = nodes.select("v", F.col("weight").cast("long").alias("a"), zero.alias("b"), F.lit(0).alias("kind"))
    rows = rows.union(arcs.select("src", "dst", F.col("w").cast("long"), F.lit(1)))
    if labels is not None:
        rows = rows.union(labels.select("v", F.col("label").cast("long"), zero, F.lit(2)))
    grow = labels is None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight: dict[int, int] = {}
        near: dict[int, dict[int, int]] = defaultdict(dict)
        old: dict[int, int] = {}
        for batch in batches:
            for v, a, b, kind in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if kind == 1:
                    near[v][a] = b
                else:
                    (old if kind else weight)[v] = a
        label = _grow_and_refine(weight, near, k, imbalance * sum(weight.values()) / k, None if grow else old)
        yield pa.RecordBatch.from_arrays([pa.array(list(label), pa.int64()), pa.array(list(label.values()), pa.int32())], names=["v", "label"])

    return durable(rows.coalesce(1).mapInArrow(run, "v long, label int"))


def _refine_in_spark(nodes: DataFrame, arcs: DataFrame, labels: DataFrame, k: int, imbalance: float, seed: int, passes: int = 4) -> DataFrame:
    """Refinement of a level that doesn't fit in one task: throttled moves of positive gain, node weights as loads."""
    from graphpart.operators.engine import FixedIterations, run_loop

    strength = arcs.groupBy(F.col("src").alias("v")).agg(F.sum("w").alias("wdeg"))
    verts = durable(nodes.join(strength, "v", "left").select("v", F.col("weight").alias("deg"), F.coalesce("wdeg", F.lit(0)).alias("wdeg")))
    return run_loop(arcs, verts, labels, list(range(k)), c=imbalance, seed=seed, halting=FixedIterations(passes)).labels


def multilevel_partition(edges: DataFrame, k: int, imbalance: float = 1.03, directed: bool = True, seed: int = 42, coarse_target: int | None = None, unit: str = "degree") -> DataFrame:
    """Coarsen by heavy-edge matching in Spark, partition the coarse graph in one task, project back and refine each level, in Spark where it doesn't fit in one task."""
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    nodes = durable(convert.vertex_stats(arcs).select("v", st.load_of(unit).alias("weight")))
    levels, target, n = [], coarse_target or max(20 * k, 2000), nodes.count()
    while n > target:
        up = durable(_match(nodes, arcs, seed, len(levels)))
        finer = (nodes, arcs)
        nodes, arcs = contract(nodes, arcs, up)
        levels.append((up, finer))
        was, n = n, nodes.count()
        if n > 0.9 * was:
            break
    frame = _coarsest(nodes, arcs, k, imbalance, seed)
    for up, (fine_nodes, fine_arcs) in reversed(levels):
        frame = durable(up.join(frame.withColumnRenamed("v", "up"), "up").select("v", "label"))
        if _fits(fine_nodes, fine_arcs):
            frame = _in_one_task(fine_nodes, fine_arcs, k, imbalance, frame)
        else:
            frame = _refine_in_spark(fine_nodes, fine_arcs, frame, k, imbalance, seed)
    return frame


def coarsen_lpa_partition(edges: DataFrame, k: int, max_cluster: float | None = None, coarse_target: int = 2000, imbalance: float = 1.03, rounds: int = 3, directed: bool = True, seed: int = 42, unit: str = "vertices") -> DataFrame:
    """Coarsen by label propagation with a cluster size limit, partition the coarse graph in one task, project back; balances vertices unless told otherwise."""
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    nodes = durable(convert.vertex_stats(arcs).select("v", st.load_of(unit).alias("weight")))
    total, n = nodes.agg(F.sum("weight")).first()[0] or 0, nodes.count()
    cap = max_cluster or max(1.0, total / (4 * k))
    ups = []
    while n > coarse_target:
        cluster = nodes.select("v", F.col("v").alias("c"), "weight")
        for t in range(rounds):
            cluster = durable(_cluster_round(cluster, arcs, cap, seed, 10 * len(ups) + t))
        up = durable(cluster.select("v", F.col("c").alias("up")))
        ups.append(up)
        nodes, arcs = contract(nodes, arcs, up)
        was, n = n, nodes.count()
        if n > 0.9 * was:
            break
    frame = _coarsest(nodes, arcs, k, imbalance, seed)
    for up in reversed(ups):
        frame = up.join(frame.withColumnRenamed("v", "up"), "up").select("v", "label")
    return durable(frame)


def _cluster_round(cluster: DataFrame, arcs: DataFrame, cap: float, seed: int, t: int) -> DataFrame:
    """Each node moves to the neighbouring cluster of most weight; inflow is throttled to the room under the size limit."""
    size = cluster.groupBy("c").agg(F.sum("weight").alias("size"))
    h = arcs.join(cluster.select(F.col("v").alias("src"), "c"), "src").groupBy(F.col("dst").alias("v"), "c").agg(F.sum("w").alias("h"))
    tie = draw("portable", seed, t, "cluster", "v", "c")
    best = h.join(size, "c").where(F.col("size") < cap).groupBy("v").agg(F.max(F.struct("h", tie.alias("tie"), "c", "size")).alias("b"))
    want = cluster.join(best.select("v", F.col("b.c").alias("to"), F.col("b.size").alias("size")), "v", "left")
    # only half of the nodes move at a time, so that pairs don't swap
    half = draw("portable", seed, t, "half", "v") < F.lit(1 << 31)
    # read twice below: written, so that the plan isn't made and run twice
    asks = durable(want.where(F.col("to").isNotNull() & (F.col("to") != F.col("c")) & half).select("v", "to", "weight", "size"))
    m = asks.groupBy("to").agg(F.sum("weight").alias("m"))
    go = asks.join(m, "to").where(draw("portable", seed, t, "fit", "v") / F.lit(4294967296.0) < (F.lit(float(cap)) - F.col("size")) / F.col("m")).select("v", "to")
    return cluster.join(go, "v", "left").select("v", F.coalesce("to", "c").alias("c"), "weight")


def central_lpa(edges: DataFrame, k: int, slack: float = 0.05, directed: bool = True, seed: int = 42, iterations: int = 10, unit: str = "degree") -> DataFrame:
    """Label propagation with a central relocation plan between iterations: gains by (from, to) reach the driver, which sets quotas.

    The driver's input grows with k^2: what the comparison is about. Quotas are greedy by gain, opposite flows matched, in
    place of a linear program.
    """
    arcs = durable(convert.to_weighted_undirected(edges, directed))
    verts = durable(convert.vertex_stats(arcs))
    labels = durable(st.init_random(verts, k, seed))
    total = verts.agg(F.sum(st.load_of(unit))).first()[0] or 0
    from pyspark.sql import Window

    for t in range(1, iterations + 1):
        state = verts.join(labels, "v")
        h = scores.build_hist(arcs, labels).join(state.withColumnRenamed("label", "cur"), "v")
        own = F.max(F.when(F.col("label") == F.col("cur"), F.col("h")).otherwise(0))
        best = h.groupBy("v").agg(F.max(F.struct("h", (F.col("label") == F.col("cur")).alias("own"), draw("portable", seed, t, "tie", "v", "label").alias("d"), "label")).alias("b"), own.alias("own"), F.max("cur").alias("cur"), F.max(st.load_of(unit)).alias("x"))
        ask = durable(best.select("v", "cur", F.col("b.label").alias("to"), (F.col("b.h") - F.col("own")).alias("gain"), "x").where("gain > 0"))
        rows = ask.groupBy("cur", "to", "gain").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("x")).collect()
        load = {i: 0 for i in range(k)} | {r["label"]: r["b"] for r in st.partition_loads(state, unit).collect()}
        quota: dict[tuple[int, int], int] = defaultdict(int)
        lo, hi = (1 - slack) * total / k, (1 + slack) * total / k
        wish: dict[tuple[int, int], int] = defaultdict(int)
        for r in sorted(rows, key=lambda r: (-r["gain"], r["cur"], r["to"])):
            each = r["x"] / r["n"]
            fit = min(r["n"], int(max(0.0, min((hi - load[r["to"]]) / each, (load[r["cur"]] - lo) / each))))
            quota[r["cur"], r["to"]] += fit
            load[r["to"]] += int(fit * each)
            load[r["cur"]] -= int(fit * each)
            wish[r["cur"], r["to"]] += r["n"] - fit
        for a, b in list(wish):
            if a < b:
                swap = min(wish[a, b], wish.get((b, a), 0))
                quota[a, b] += swap
                quota[b, a] += swap
        plan = [(a, b, q) for (a, b), q in quota.items() if q > 0]
        if not plan:
            break
        q = edges.sparkSession.createDataFrame(plan, "cur int, to int, q long")
        rank = F.row_number().over(Window.partitionBy("cur", "to").orderBy(F.desc("gain"), draw("portable", seed, t, "rank", "v"), "v"))
        go = ask.join(F.broadcast(q), ["cur", "to"]).withColumn("rank", rank).where("rank <= q").select("v", "to")
        labels = durable(labels.join(go, "v", "left").select("v", F.coalesce("to", "label").cast("int").alias("label")))
    return labels
