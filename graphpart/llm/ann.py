"""Approximate nearest neighbours by largest inner product, over balanced posting lists.

Vectors are scaled by the table's largest component and get one coordinate more, so that all have the length of the longest:
then the largest inner product is the least distance. The number of lists grows with the table (a list for LIST_SIZE
vectors, up to MOST_LISTS); centroids come from balanced k-means on a sample of at least SAMPLE vectors and four for each list, smallest hashes first. Every
vector goes to the list of its nearest centroid, boundary vectors also to further lists about as near, unless a list chosen
before is nearer to the further centroid than the vector is. A query finds near centroids by best-first search in
a graph of them, held in memory, and reads the lists whose distance is within a ratio of the nearest one's; the
smallest ratio that reaches the recall asked for on the sample is taken. Where these lists hold too few vectors for a result, the
ratio is of the distance at which the nearest lists hold enough; a query that is short even so (ids that repeat with other
vectors) reads all lists. Where the lists read are an eighth of all or more, the centroids are scanned in place of the search.

Lists near each other form groups of bounded size, a larger list several of them. A query goes once to each group with lists
of its own, however many these are, so neither rows nor a task's memory grow with the number of lists.

Equal vectors are one entry with their smallest ids, as many as any result can need, so a vector that a third of the
rows share is one row of one list. Scores are exact doubles on the original vectors.

A product beyond the range of doubles is infinite, as double precision has it. Edge cases: vectors that are null, zero, hold null or non-finite components, or have not the table's most frequent length take no part,
nor do rows without an id; a repeated id with one vector counts once; ties go to the smaller id; with no more than TOP
candidates all are returned; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import batched, chain, groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.llm.common import BATCH_ROWS, arrow_map, durable
from graphpart.session import release

TOP = 20
SAMPLE, MOST_LISTS, LIST_SIZE = 12_000, 16_384, 200
CELLS = 1 << 21  # distances or products held at a time (16 MB)
REPLICAS, SLACK = 4, 1.12
LEAST_GROUP, GROUP, GROUP_BYTES = 4000, 32_768, 1 << 24  # members of a group, and bytes of their doubles
HELD = 20_000  # distinct vectors that a task holds at a time while it gathers their ids
PENDING = 400_000  # pairs of 24 bytes


def _step(width: int) -> int:
    """Rows of ``width`` cells that are held at a time."""
    return max(1, CELLS // max(1, width))


def _stored(table: DataFrame, vec_col: str) -> type:
    """How vectors are kept as bytes: floats as they are, all else as doubles."""
    return np.float32 if table.schema[vec_col].dataType.elementType.typeName() == "float" else np.float64


def _components(batch: pa.RecordBatch, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """The vectors of a batch, and which take part: all components there and finite (null reads as NaN), some not zero."""
    m = batch.column("v").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim) + 0.0  # one zero
    return m, np.isfinite(m).all(axis=1) & (m != 0).any(axis=1)


def valid_vectors(table: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """(vec, ids): distinct valid vectors as bytes (see ``_stored``), with their TOP + 1 smallest ids."""
    kept = _stored(table, vec_col)
    v = F.transform(F.col(vec_col), lambda x: x.cast("double"))
    rows = table.where(F.col(id_col).isNotNull() & F.col(vec_col).isNotNull() & (F.size(vec_col) > 0)).select(F.col(id_col).cast("long").alias("id"), v.alias("v"))
    top = rows.groupBy(F.size("v").alias("dim")).count().orderBy(F.desc("count"), F.desc("dim")).limit(1).collect()
    if not top:
        return table.sparkSession.createDataFrame([], "vec binary, ids array<bigint>")
    dim = top[0]["dim"]

    def told(held: dict[bytes, list[int]]) -> Iterator[pa.RecordBatch]:
        for some in batched(held.items(), BATCH_ROWS):
            yield pa.RecordBatch.from_arrays([pa.array([v for v, _ in some], pa.binary()), pa.array([sorted(-x for x in ids) for _, ids in some], pa.list_(pa.int64()))], names=["vec", "ids"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, list[int]] = {}
        for batch in batches:
            m, ok = _components(batch, dim)
            m = m.astype(kept)
            for i, key in zip(np.flatnonzero(ok).tolist(), batch.column("id").filter(pa.array(ok)).to_pylist(), strict=True):
                ids = held.setdefault(m[i].tobytes(), [])
                if len(ids) <= TOP:
                    if -key not in ids:
                        heapq.heappush(ids, -key)
                elif -key > ids[0] and -key not in ids:
                    heapq.heapreplace(ids, -key)
            if len(held) >= HELD:
                yield from told(held)
                held = {}
        yield from told(held)

    part = arrow_map(rows.where(F.size("v") == dim), run, "vec binary, ids array<bigint>")
    return part.groupBy("vec").agg(F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, TOP + 1).alias("ids"))


def _matrix(vecs: list[bytes], kept: type) -> np.ndarray:
    return np.frombuffer(b"".join(vecs), kept).reshape(len(vecs), -1).astype(np.float64)


def _lift(x: np.ndarray, longest: float) -> np.ndarray:
    """One coordinate more, so that all have the squared length ``longest``."""
    return np.hstack([x, np.sqrt(np.maximum(0, longest - (x * x).sum(axis=1)))[:, None]])


def _distances(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0, (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)))


def balanced_centroids(x: np.ndarray, k: int, rounds: int = 12, seed: int = 3) -> np.ndarray:
    """k-means whose squared distances are raised for lists above the mean size."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)].copy()
    price, step = np.zeros(k), _step(k)
    for _ in range(rounds):
        at, near = np.empty(len(x), np.int64), np.empty(len(x))
        for lo in range(0, len(x), step):
            d = _distances(x[lo : lo + step], c) ** 2
            at[lo : lo + step], near[lo : lo + step] = (d + price).argmin(axis=1), d.min(axis=1)
        size = np.bincount(at, minlength=k)
        price = np.maximum(0, price + 0.1 * near.mean() * (size * k / len(x) - 1))
        total = np.zeros_like(c)
        np.add.at(total, at, x)
        c = np.where(size[:, None] > 0, total / np.maximum(size, 1)[:, None], x[rng.choice(len(x), k)])
    return c


class CentroidGraph:
    """Neighbour lists of the centroids, both ways, and best-first search in them."""

    def __init__(self, c: np.ndarray, degree: int = 16) -> None:
        self.c = c
        near = np.concatenate([self._nearest(lo, degree) for lo in range(0, len(c), _step(len(c)))])
        sets = [set(row.tolist()) for row in near]
        for i, row in enumerate(near.tolist()):
            for j in row:
                sets[j].add(i)
        order = np.random.default_rng(1).permutation(len(c)).tolist()
        for a, b in zip(order, order[1:] + order[:1], strict=True):  # a ring keeps the graph connected
            if a != b:
                sets[a].add(b)
        self.near = [np.array(sorted(s), np.int64) for s in sets]
        self.entry = int(((c - c.mean(axis=0)) ** 2).sum(axis=1).argmin())

    def _nearest(self, lo: int, degree: int) -> np.ndarray:
        d = _distances(self.c[lo : lo + _step(len(self.c))], self.c)
        d[np.arange(len(d)), np.arange(lo, lo + len(d))] = np.inf
        return np.argsort(d, axis=1, kind="stable")[:, : min(degree, len(self.c) - 1)]

    def search(self, q: np.ndarray, ratio: float, width: int = 32) -> np.ndarray:
        """Centroids within ``ratio`` of the nearest distance, nearest first; ``width`` further ones are looked at before it ends."""
        seen = np.zeros(len(self.c), bool)
        seen[self.entry] = True
        d0 = float(np.sqrt(((self.c[self.entry] - q) ** 2).sum()))
        heap, found, best = [(d0, self.entry)], [(d0, self.entry)], d0
        worse = 0
        while heap:
            d, i = heapq.heappop(heap)
            worse = 0 if d <= best * ratio else worse + 1
            if worse > width:
                break
            new = self.near[i][~seen[self.near[i]]]
            if new.size:
                seen[new] = True
                for x, j in zip(np.sqrt(((self.c[new] - q) ** 2).sum(axis=1)).tolist(), new.tolist(), strict=True):
                    heapq.heappush(heap, (x, j))
                    found.append((x, j))
                    best = min(best, x)
        found.sort()
        return np.array([j for x, j in found if x <= best * ratio + 1e-12], np.int64)

    def enough(self, q: np.ndarray, ratio: float, held: np.ndarray, need: int = TOP + 1) -> np.ndarray:
        """As ``search``; if those lists hold under ``need`` vectors, all within ``ratio`` of the distance at which the nearest lists do."""
        found = self.search(q, ratio)
        if held[found].sum() >= need:
            return found
        return self._enough(np.sqrt(((self.c - q) ** 2).sum(axis=1)), ratio, held, need)

    def scan(self, q: np.ndarray, ratio: float, held: np.ndarray, need: int = TOP + 1) -> list[np.ndarray]:
        """``enough`` for each row of q from the distances to all centroids."""
        out = []
        for d in _distances(q, self.c):
            found = np.flatnonzero(d <= d.min() * ratio + 1e-12)
            out.append(found if held[found].sum() >= need else self._enough(d, ratio, held, need))
        return out

    def _enough(self, d: np.ndarray, ratio: float, held: np.ndarray, need: int) -> np.ndarray:
        order = np.argsort(d, kind="stable")
        last = int(np.searchsorted(np.cumsum(held[order]), need))
        return order if last == order.size else order[d[order] <= d[order[last]] * ratio + 1e-12]


def lists_of(x: np.ndarray, graph: CentroidGraph) -> list[list[int]]:
    """Posting lists of each (lifted) vector: the nearest, and further ones by the closure rule."""
    out, step = [], _step(len(graph.c))
    for lo in range(0, len(x), step):
        d = _distances(x[lo : lo + step], graph.c)
        most = min(REPLICAS * 2, d.shape[1])
        near = np.argpartition(d, most - 1, axis=1)[:, :most]
        near = np.take_along_axis(near, np.lexsort((near, np.take_along_axis(d, near, axis=1)), axis=1), axis=1)
        for row, order in zip(d, near.tolist(), strict=True):
            chosen = [order[0]]
            for j in order[1:]:
                if len(chosen) == REPLICAS or row[j] > SLACK * row[order[0]]:
                    break
                if (((graph.c[chosen] - graph.c[j]) ** 2).sum(axis=1) >= row[j] ** 2).all():
                    chosen.append(j)
            out.append(chosen)
    return out


def tuned_ratio(x: np.ndarray, graph: CentroidGraph, goal: float, queries: int = 120) -> float:
    """The smallest ratio of a ladder at which the sample's own neighbours are found in the lists read."""
    flat = x[:, :-1]
    pick = np.linspace(0, len(x) - 1, min(queries, len(x))).astype(int)
    member = lists_of(x, graph)
    score = flat[pick] @ flat.T
    score[np.arange(pick.size), pick] = -np.inf
    want = np.argsort(-score, axis=1, kind="stable")[:, : min(TOP, len(x) - 1)]
    if not want.size:
        return 1.0
    for ratio in [1.0 + 0.02 * i for i in range(51)]:
        hits = []
        for p, near in zip(pick, want.tolist(), strict=True):
            read = set(graph.search(np.append(flat[p], 0.0), ratio).tolist())
            hits.append(np.mean([not read.isdisjoint(member[w]) for w in near]))
        if np.mean(hits) >= goal:
            return ratio
    return 1e9


def grouped(c: np.ndarray, sizes: np.ndarray, most: int) -> list[np.ndarray]:
    """Lists in groups of at most ``most`` members (or of one list), near ones together: halved along the widest direction."""
    out, todo = [], [np.arange(len(c))]
    while todo:
        some = todo.pop()
        if some.size == 1 or sizes[some].sum() <= most:
            out.append(some)
            continue
        x = c[some] - c[some].mean(axis=0)
        some = some[np.argsort(x @ np.linalg.eigh(x.T @ x)[1][:, -1], kind="stable")]
        total = np.cumsum(sizes[some])
        cut = min(max(1, int(np.searchsorted(total, total[-1] / 2))), some.size - 1)
        todo += [some[cut:], some[:cut]]
    return out


def _queries(table: DataFrame, id_col: str, vec_col: str, every: int, dim: int) -> DataFrame:
    """(id, vec) of the distinct valid query rows, vectors as bytes."""
    kept = _stored(table, vec_col)
    v = F.transform(F.col(vec_col), lambda x: x.cast("double"))
    rows = table.where((F.pmod(F.col(id_col).cast("long"), F.lit(every)) == 0) & (F.size(vec_col) == dim)).select(F.col(id_col).cast("long").alias("id"), v.alias("v"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            m, ok = _components(batch, dim)
            yield pa.RecordBatch.from_arrays([batch.column("id").filter(pa.array(ok)), pa.array([row.tobytes() for row in m[ok].astype(kept)], pa.binary())], names=["id", "vec"])

    return arrow_map(rows, run, "id long, vec binary").distinct()


class _Nearest:
    """The nearest of many queries (number, id), from parts that may name a vector twice; what waits is reduced before it outgrows the rest."""

    def __init__(self) -> None:
        self.at: dict[tuple[int, int], int] = {}
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.pending = 0
        self.least = np.zeros(0)

    def bar(self, keys: list[tuple[int, int]]) -> np.ndarray:
        """For each query a score that TOP vectors are known to reach; minus infinity if none is."""
        at = np.array([self.at.get(k, -1) for k in keys], np.int64)
        known = (at >= 0) & (at < self.least.size)
        return np.where(known, self.least[np.where(known, at, 0)], -np.inf) if self.least.size else np.full(at.size, -np.inf)

    def add(self, keys: list[tuple[int, int]], of: np.ndarray, ids: np.ndarray, scores: np.ndarray) -> None:
        """Vectors ``ids`` with their scores for the queries keys[of]."""
        at = np.array([self.at.setdefault(k, len(self.at)) for k in keys], np.int64)
        self.parts.append((at[of], ids, scores))
        self.pending += ids.size
        if self.pending > max(PENDING // 4, 2 * TOP * len(self.at)):
            self.reduce()

    def full(self) -> bool:
        return len(self.at) * TOP > PENDING // 2

    def reduce(self) -> None:
        q, ids, sc = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        order = np.lexsort((ids, q))
        q, ids, sc = q[order], ids[order], sc[order]
        new = np.ones(q.size, bool)
        new[1:] = (q[1:] != q[:-1]) | (ids[1:] != ids[:-1])
        q, ids, sc = q[new], ids[new], sc[new]
        order = np.lexsort((ids, -sc, q))
        q, ids, sc = q[order], ids[order], sc[order]
        rank = np.arange(q.size) - np.searchsorted(q, q)
        self.least = np.full(len(self.at), -np.inf)
        self.least[q[rank == TOP - 1]] = sc[rank == TOP - 1]
        keep = rank < TOP
        self.parts = [(q[keep], ids[keep], sc[keep])]
        self.pending = 0

    def flush(self) -> pa.RecordBatch:
        """One row of each query, nearest first; nothing is held after."""
        numbers, keys = [q for q, _ in self.at], [k for _, k in self.at]
        ids, sc = np.zeros(0, np.int64), np.zeros(0)
        ends = np.zeros(len(keys) + 1, np.int32)
        if self.parts:
            self.reduce()
            q, ids, sc = self.parts[0]
            ends = np.searchsorted(q, np.arange(len(keys) + 1)).astype(np.int32)
        self.__init__()
        lists = [pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(x)) for x in (ids, sc)]
        return pa.RecordBatch.from_arrays([pa.array(numbers, pa.int64()), pa.array(keys, pa.int64()), *lists], names=["q", "query_id", "ids", "scores"])


def _reached(rough: np.ndarray) -> np.ndarray:
    """For each row a value that TOP + 1 of its cells reach, as near below the greatest of these as maxima of 256 parts tell."""
    n, width = rough.shape
    parts, need = rough, min(TOP + 1, width)
    if width >= 2048:
        each = width // 256
        parts = rough[:, : each * 256].reshape(n, 256, each).max(axis=2)
    last = parts.shape[1] - need
    return np.partition(parts, last, axis=1)[:, last]


def nearest_neighbours(table: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", every: int = 20, goal: float = 0.95) -> DataFrame:
    """(query_id, rank, vec_id, score): the TOP nearest of each query (id divisible by ``every``) among all other rows."""
    spark, kept = table.sparkSession, _stored(table, vec_col)
    entries = durable(valid_vectors(table, id_col, vec_col))
    n = entries.count()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    if not n:
        return empty
    k = max(1, min(MOST_LISTS, n // LIST_SIZE))
    sample = _matrix([r["vec"] for r in entries.select("vec").orderBy(F.xxhash64("vec"), "vec").limit(max(SAMPLE, 4 * k)).collect()], kept)
    dim = sample.shape[1]

    def greatest(of) -> float:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            most = max((float(of(_matrix(b.column(0).to_pylist(), kept))) for b in batches if b.num_rows), default=0.0)
            yield pa.RecordBatch.from_arrays([pa.array([most])], names=["most"])

        return arrow_map(entries.select("vec"), run, "most double").agg(F.max("most")).first()[0]

    scale = greatest(lambda x: np.abs(x).max())
    longest = greatest(lambda x: ((x / scale) ** 2).sum(axis=1).max()) * (1 + 1e-12)
    lifted = _lift(sample / scale, longest)
    graph = CentroidGraph(balanced_centroids(lifted, max(1, min(k, len(sample) // 4))))
    ratio = tuned_ratio(lifted, graph, goal)
    some = lifted[:: max(1, len(lifted) // 50)][:, :-1]
    wide = 8 * np.mean([graph.search(np.append(v, 0.0), ratio).size for v in some]) >= len(graph.c)
    shared = spark.sparkContext.broadcast((graph, ratio, longest))  # at most MOST_LISTS centroids and their neighbours

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, _, most = shared.value
        for batch in batches:
            vecs, ids = batch.column("vec").to_pylist(), batch.column("ids").to_pylist()
            lists = lists_of(_lift(_matrix(vecs, kept) / scale, most), g)
            at = [i for i, ls in enumerate(lists) for _ in ls]
            own = [not n for ls in lists for n in range(len(ls))]
            yield pa.RecordBatch.from_arrays([pa.array([j for ls in lists for j in ls], pa.int32()), pa.array([vecs[i] for i in at], pa.binary()), pa.array([ids[i] for i in at], pa.list_(pa.int64())), pa.array(own, pa.bool_())], names=["list", "vec", "ids", "own"])

    posted = durable(arrow_map(entries, post, "list int, vec binary, ids array<bigint>, own boolean"))
    release(entries)
    held_in, counts = np.zeros(len(graph.c), np.int64), np.zeros(len(graph.c), np.int64)  # a vector is held in its nearest list alone
    for r in posted.groupBy("list").agg(F.count(F.lit(1)).alias("count"), F.count_if("own").alias("own")).collect():  # at most MOST_LISTS rows
        held_in[r["list"]], counts[r["list"]] = r["own"], r["count"]
    # groups: enough of them for all cores, each small enough for a task; a list over that size lies in several
    most = max(1, min(GROUP, GROUP_BYTES // (8 * dim), max(LEAST_GROUP, int(counts.sum()) // (3 * spark.sparkContext.defaultParallelism))))
    first, parts, slot, width = (np.zeros(len(graph.c), np.int64) for _ in range(4))
    at = 0
    for lists in grouped(graph.c, counts, most):
        first[lists], parts[lists], slot[lists], width[lists] = at, max(1, -(-int(counts[lists].sum()) // most)) if lists.size == 1 else 1, np.arange(lists.size), lists.size
        at += int(parts[lists[0]])
    own_of = lambda values: F.element_at(F.lit(values.tolist()), F.col("list") + 1)
    group = own_of(first) + F.pmod(F.xxhash64("vec"), own_of(parts))
    members = posted.select(group.cast("int").alias("group"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("q"), F.lit(None).cast("long").alias("id"), own_of(slot).cast("int").alias("slot"), "vec", "ids", F.lit(None).cast("binary").alias("read"))
    asked = durable(_queries(table, id_col, vec_col, every, dim).withColumn("q", F.monotonically_increasing_id()))
    schema = "group int, kind int, q long, id long, slot int, vec binary, ids array<bigint>, read binary"

    def asks_of(found: np.ndarray) -> Iterator[tuple[int, bytes]]:
        """The groups of some lists, and which of a group's lists are meant (as bits)."""
        found = found[counts[found] > 0]
        found = found[np.argsort(first[found], kind="stable")]
        base, start = np.unique(first[found], return_index=True)
        for b, lists in zip(base.tolist(), np.split(found, start[1:]) if found.size else [], strict=True):
            bits = np.zeros(int(width[lists[0]]), np.uint8)
            bits[slot[lists]] = 1
            for part in range(int(parts[lists[0]])):
                yield b + part, np.packbits(bits).tobytes()

    def ask(batches: Iterator[pa.RecordBatch], everywhere: bool = False) -> Iterator[pa.RecordBatch]:
        g, r, _ = shared.value

        def rows() -> Iterator[tuple]:
            for batch in batches:
                step = _step(len(g.c))
                for part in (batch.slice(i, step) for i in range(0, batch.num_rows, step)):
                    vecs = part.column("vec").to_pylist()
                    x = np.hstack([_matrix(vecs, kept) / scale, np.zeros((len(vecs), 1))])
                    if everywhere:
                        found = [np.arange(len(g.c))] * len(vecs)
                    else:
                        found = g.scan(x, r, held_in) if wide else [g.enough(v, r, held_in) for v in x]
                    for q, key, vec, lists in zip(part.column("q").to_pylist(), part.column("id").to_pylist(), vecs, found, strict=True):
                        for of, bits in asks_of(lists):
                            yield of, q, key, vec, bits

        for some in batched(rows(), BATCH_ROWS):  # however many groups a query asks, batches stay small
            of, q, key, vec, bits = zip(*some, strict=True)
            k = len(of)
            yield pa.RecordBatch.from_arrays(
                [pa.array(of, pa.int32()), pa.array(np.ones(k, np.int32)), pa.array(q, pa.int64()), pa.array(key, pa.int64()), pa.nulls(k, pa.int32()), pa.array(vec, pa.binary()), pa.nulls(k, pa.list_(pa.int64())), pa.array(bits, pa.binary())],
                names=["group", "kind", "q", "id", "slot", "vec", "ids", "read"],
            )

    def compare(batches: Iterator[pa.RecordBatch], everywhere: bool = False) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(8)), strict=True))
        held = _Nearest()
        for _, block in groupby(rows, key=lambda r: r[0]):
            vecs: dict[bytes, int] = {}
            ids_of: list[list[int]] = []
            lists: dict[int, list[int]] = {}
            queries: Iterator[tuple] = iter(())
            for r in block:
                if r[1]:
                    queries = chain([r], block)
                    break
                i = vecs.setdefault(r[5], len(vecs))  # a vector may stand in several lists of a group
                if i == len(ids_of):
                    ids_of.append(r[6])
                lists.setdefault(r[4], []).append(i)
            if not vecs:
                continue
            x = _matrix(list(vecs), kept)
            vecs.clear()
            count = np.array([len(i) for i in ids_of])
            start, ids = np.cumsum(count) - count, np.array([i for some in ids_of for i in some], np.int64)
            del ids_of
            inside = {j: np.array(of, np.int64) for j, of in lists.items()}
            scaled = x / scale
            by_id = np.argsort(ids, kind="stable")
            owner, each = np.repeat(np.arange(count.size), count)[by_id], np.flatnonzero(np.diff(ids[by_id], prepend=ids[by_id[0]] - 1))

            def offer(some: list[tuple], asked_here: np.ndarray, pick: np.ndarray | None, x=x, scaled=scaled, count=count, start=start, ids=ids, owner=owner, each=each) -> None:
                own = np.abs(asked_here).max(axis=1)
                rough = (asked_here / own[:, None]) @ (scaled if pick is None else scaled[pick]).T  # of whatever lengths, these are finite
                keys = [s[2:4] for s in some]
                # a query that came short may have met few ids with many vectors: then the best of each id counts
                best_of = np.maximum.reduceat(rough[:, owner], each, axis=1) if everywhere else rough
                least = np.maximum(_reached(best_of), held.bar(keys) / own / scale)
                at, near = np.nonzero(rough >= (least - 1e-9)[:, None])
                near = near if pick is None else pick[near]
                with np.errstate(over="ignore"):
                    exact = (x[near] * asked_here[at]).sum(axis=1)
                n = count[near]
                which = np.repeat(start[near] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                at, exact, found = np.repeat(at, n), np.repeat(exact, n), ids[which]
                keep = found != np.array([s[3] for s in some])[at]
                held.add(keys, at[keep], found[keep], exact[keep])

            for some in batched(queries, min(256, max(16, _step(len(x))))):
                asked_here = _matrix([s[5] for s in some], kept)
                size = max(len(s[7]) for s in some)
                read = np.unpackbits(np.frombuffer(b"".join(s[7] for s in some), np.uint8).reshape(len(some), size), axis=1).astype(bool)
                if everywhere or 4 * sum(int(read[:, j].sum()) * of.size for j, of in inside.items()) >= len(some) * len(x):
                    offer(list(some), asked_here, None)  # most of the group is read: all of it in one product
                else:
                    for j, of in inside.items():
                        who = np.flatnonzero(read[:, j])
                        if who.size:
                            offer([some[i] for i in who.tolist()], asked_here[who], of)
                if held.full():
                    yield held.flush()
        yield held.flush()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True))
        held = _Nearest()
        for key, some in groupby(rows, key=lambda r: r[:2]):
            if held.full():
                yield held.flush()
            for r in some:
                held.add([key], np.zeros(len(r[2]), np.int64), np.array(r[2], np.int64), np.array(r[3], np.float64))
        yield held.flush()

    out = "q long, query_id long, ids array<bigint>, scores array<double>"

    def answers(queries: DataFrame, everywhere: bool) -> DataFrame:
        both = members.union(arrow_map(queries.select("q", "id", "vec"), lambda batches: ask(batches, everywhere), schema))
        found = arrow_map(both.repartition("group").sortWithinPartitions("group", "kind"), lambda batches: compare(batches, everywhere), out)
        return arrow_map(found.repartition("q").sortWithinPartitions("q", "query_id"), merge, out)

    best = answers(asked, False)
    if len(graph.c) > 1:
        best = durable(best)
        done = best.where(F.size("ids") >= TOP)
        short = durable(asked.join(done.select("q"), "q", "left_anti"))
        if not short.isEmpty():
            best = done.union(answers(short, True))
    ranked = best.select("query_id", F.posexplode(F.arrays_zip("ids", "scores")).alias("at", "b"))
    return ranked.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("b.ids").alias("vec_id"), F.col("b.scores").alias("score"))
