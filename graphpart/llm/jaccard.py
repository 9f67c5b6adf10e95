"""N-gram Jaccard join: all texts whose sets of 5-word shingles have a similarity of 0.75 or more, as linked classes.

Shingles are 64-bit hashes, a text's set is a sorted array, and equal sets count as one text from the start. Then:

1. Of each set only the smallest hashes, about three eighths, are dealt out by hash. Two linked sets of n and m shingles
   share at least a known number of them, so a set that meets too few others' there links with nothing and rests.
2. The full sets of the others are dealt out by hash. Where several sets meet, each is counted against the smallest
   of them: a count high enough proves the link, without any set having been moved. The same pass tells how
   rare a set's shingles are; with over a quarter of its own alone it links with nothing.
3. Dealt out again, sets that meet at one of the rarest quarter of both, which linked sets must, fall into the same
   neighbourhood; a passage that many texts share is not among the rarest and joins none of them.
4. A neighbourhood whose sets are one class already is done, however many there are. In the others, sets go to tiles of
   bounded size, those of a large neighbourhood by bands of set sizes first. In a tile, sets are ordered by size and compared within the band of sizes that 0.75 allows; hashed
   bitmaps bound the overlap from above by bit counts, and what passes is counted exactly on the sorted arrays. Pairs that
   are of one class by then need no comparison.

No pairs of a group are ever written out: a group of c copies costs c rows, and every link between different texts is either
found or implied by those found. Counts and classes are of all rows and whole texts.

Edge cases: a null text or one without words has an empty set, class its own id, linked with nothing; fewer than five
words make one shingle of the whole sequence; repeated rows are copies; a class of rows without an id has a null class id;
extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from graphpart.llm.common import ID, TEXT, arrow_map, durable, strings
from graphpart.llm.components import connected

WORDS = 5
CACHE_WORDS = 250_000
MOST_BROADCAST = 1_000_000  # rows of 24 bytes
HOT_CLASS = 1000  # members of a class whose smallest id is broadcast
TILE_SETS = 1500
TASK_BYTES, MOST_TASKS = 64 << 20, 100_000
_U = np.uint64
_LOW48 = _U((1 << 48) - 1)


class WordHasher(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


_HASHER = WordHasher()


def shingle_set(text: str) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles; words are cut at ASCII white space, A-Z lower-cased."""
    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(_HASHER.__getitem__, words), np.uint64, len(words))
    k = min(WORDS, len(words))
    h = np.full(len(words) - k + 1, 0x9E3779B97F4A7C15 * k & (1 << 64) - 1, np.uint64)
    for i in range(k):
        h = (h ^ w[i : len(w) - k + 1 + i]) * _U(0xD6E8FEB86659FD93)
        h ^= h >> _U(32)
    return np.unique(h)


def set_key(s: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes()) - (1 << 63)


def least_shared(n: int) -> int:
    """How many of the other's shingles any linked set has at least: 3/4 of n, rounded up."""
    return (3 * n + 3) // 4


def long_prefix(n: int) -> int:
    return min(n, n - least_shared(n) + n // 8 + 1)


_ROW = "kind int, bucket int, doc_id long, sk long, n int, elems binary, sks binary, marks binary"
_NAMES = [c.split()[0] for c in _ROW.split(", ")]


def _rows(kind: int, **cols) -> pa.RecordBatch:
    types = {"bucket": pa.int32(), "doc_id": pa.int64(), "sk": pa.int64(), "n": pa.int32(), "elems": pa.binary(), "sks": pa.binary(), "marks": pa.binary()}
    size = len(next(iter(cols.values())))
    arrays = [pa.array(np.full(size, kind, np.int32))]
    for name, t in types.items():
        arrays.append((cols[name] if isinstance(cols[name], pa.Array) else pa.array(cols[name], t)) if name in cols else pa.nulls(size, t))
    return pa.RecordBatch.from_arrays(arrays, names=_NAMES)


def _dealt(kind: int, elems: np.ndarray, sks: np.ndarray, marks: np.ndarray | None, buckets: int, wide: int) -> pa.RecordBatch:
    """One row for each bucket of hashes: the hashes in ``wide`` bytes each, the keys of their sets, and marks."""
    bucket = (elems % _U(buckets)).astype(np.uint16 if buckets < 1 << 16 else np.uint32)
    order = np.argsort(bucket, kind="stable")
    at = np.flatnonzero(np.r_[True, np.diff(bucket[order]) != 0]) if order.size else np.zeros(0, np.int64)
    e = np.ascontiguousarray(elems[order]).view(np.uint8).reshape(-1, 8)[:, :wide].tobytes()
    s, m, end = sks[order].tobytes(), marks[order].tobytes() if marks is not None else b"", [*at.tolist(), order.size]
    spans = list(zip(end[:-1], end[1:], strict=True))
    cols = {"bucket": bucket[order][at].astype(np.int32), "elems": [e[a * wide : b * wide] for a, b in spans], "sks": [s[a * 8 : b * 8] for a, b in spans]}
    if marks is not None:
        cols["marks"] = [m[a:b] for a, b in spans]
    return _rows(kind, **cols)


def _packed(kind: int, a: np.ndarray, b: np.ndarray, counts: np.ndarray, buckets: int) -> pa.RecordBatch:
    """Counts of pairs (a, b) found by one task: a row for each bucket of a, not one for each pair."""
    bucket = (a.astype(np.uint64) % _U(buckets)).astype(np.uint32)
    order = np.argsort(bucket, kind="stable")
    at = np.flatnonzero(np.r_[True, np.diff(bucket[order]) != 0]) if order.size else np.zeros(0, np.int64)
    spans = list(zip(at.tolist(), [*at.tolist()[1:], order.size], strict=True))
    cols = [np.ascontiguousarray(x[order].astype(t)).tobytes() for x, t in ((a, np.int64), (b, np.int64), (counts, np.int32))]
    cut = lambda data, wide: [data[x * wide : y * wide] for x, y in spans]
    return _rows(kind, bucket=bucket[order][at].astype(np.int32), elems=cut(cols[0], 8), sks=cut(cols[1], 8), marks=cut(cols[2], 4))


def _totals(packed: DataFrame, docs: DataFrame) -> DataFrame:
    """(kind, sk: a, doc_id: b, n): packed counts dealt by a and summed; rows of other kinds as they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: dict[int, tuple[list, list, list]] = {}
        for batch in batches:
            blob = np.asarray(batch.column("elems").is_valid())
            if not blob.all():
                yield batch.filter(pa.array(~blob))
            for kind, *data in zip(*(batch.column(c).to_pylist() for c in ("kind", "elems", "sks", "marks")), strict=True):
                if data[0] is not None:
                    for to, x in zip(parts.setdefault(kind, ([], [], [])), data, strict=True):
                        to.append(x)
        for kind, (a, b, c) in parts.items():
            x, y, n = np.frombuffer(b"".join(a), np.int64), np.frombuffer(b"".join(b), np.int64), np.frombuffer(b"".join(c), np.int32)
            order = np.lexsort((y, x))
            x, y, n = x[order], y[order], n[order]
            new = np.flatnonzero(np.r_[True, (x[1:] != x[:-1]) | (y[1:] != y[:-1])])
            yield _rows(kind, sk=x[new], doc_id=y[new], n=np.add.reduceat(n, new).astype(np.int32))

    return durable(arrow_map(_by_bucket(packed, docs), run, _ROW).select("kind", "doc_id", "sk", "n"))


def _gathered(batches: Iterator[pa.RecordBatch], wide: int) -> tuple[list[pa.RecordBatch], np.ndarray, np.ndarray, np.ndarray]:
    """Rows that are no hashes, and the hashes, set keys and marks of the others, by hash, then key, each pair once."""
    rest, e, s, m = [], [], [], []
    for batch in batches:
        blob = np.asarray(batch.column("elems").is_valid())
        if not blob.all():
            rest.append(batch.filter(pa.array(~blob)))
        for name, to in (("elems", e), ("sks", s), ("marks", m)):
            to += [x for x in batch.column(name).to_pylist() if x is not None]
    raw = np.frombuffer(b"".join(e), np.uint8).reshape(-1, wide)
    full = np.zeros((len(raw), 8), np.uint8)
    full[:, :wide] = raw
    elems, sks = full.view(np.uint64).ravel(), np.frombuffer(b"".join(s), np.int64)
    marks = np.frombuffer(b"".join(m), np.uint8) if m else np.zeros(elems.size, np.uint8)
    order = np.argsort(elems, kind="stable")
    elems = elems[order]
    # only where a hash occurs again does the order of keys matter
    again = np.zeros(elems.size, bool)
    same = elems[1:] == elems[:-1]
    again[1:] |= same
    again[:-1] |= same
    hot = np.flatnonzero(again)
    order[hot] = order[hot][np.lexsort((sks[order[hot]], elems[hot]))]
    sks, marks = sks[order], marks[order]
    new = np.ones(elems.size, bool)
    new[1:] = ~same | (sks[1:] != sks[:-1])
    return rest, elems[new], sks[new], marks[new]


def _groups(elems: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First place and size of the group of each row."""
    first = np.flatnonzero(np.r_[True, elems[1:] != elems[:-1]]) if elems.size else np.zeros(0, np.int64)
    size = np.diff(np.r_[first, elems.size])
    return np.repeat(first, size), np.repeat(size, size)


def _tasks(df: DataFrame) -> int:
    """Tasks that hashes are dealt to: one for TASK_BYTES of input, as the plan estimates it, or as many as Spark is set to."""
    set_to = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(set_to, min(MOST_TASKS, size // TASK_BYTES)) if size < 1 << 60 else set_to  # beyond, the plan knows no size


def _buckets(df: DataFrame) -> int:
    return max(256, 4 * _tasks(df))


def _by_bucket(dealt: DataFrame, docs: DataFrame) -> DataFrame:
    n = _tasks(docs)
    return dealt.repartition("bucket") if n == int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")) else dealt.repartition(n, "bucket")


def _texts_of(docs: DataFrame, chosen: DataFrame, n_chosen: int) -> DataFrame:
    """(text, and the columns of chosen) for the rows whose id is chosen.rep."""
    side = F.broadcast(chosen) if n_chosen <= MOST_BROADCAST else chosen
    return docs.select(F.col(ID).cast("long").alias("_id"), TEXT).join(side, F.col("_id").eqNullSafe(F.col("rep"))).drop("_id")


def _linked(shared: Column, n: Column, m: Column) -> Column:
    return 4 * shared >= 3 * (n + m - shared)


def first_pass(docs: DataFrame) -> DataFrame:
    """kind 0: (doc_id, sk, n) of each row; kind 1: (sk, n) with how many hashes of the long prefix other sets have too."""
    buckets = _buckets(docs)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, sizes, elems, seen = [], [], [], {}
            for text in strings(batch, TEXT):
                s = shingle_set(text)
                k = set_key(s)
                keys.append(k)
                sizes.append(s.size)
                if s.size and k not in seen:
                    part = s[: long_prefix(s.size)]
                    seen[k] = part.size
                    elems.append(part)
            # rows are dealt by their own ids, not by sets, so that copies spread
            spread = [xxhash.xxh3_64_intdigest(f"{x}:{i}") % buckets for i, x in enumerate(batch.column(0).to_pylist())]
            yield _rows(0, bucket=spread, doc_id=batch.column(0), sk=keys, n=sizes)
            if elems:
                yield _dealt(1, np.concatenate(elems) & _LOW48, np.repeat(np.fromiter(seen, np.int64), list(seen.values())), None, buckets, 6)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest, elems, sks, _ = _gathered(batches, 6)
        yield from rest
        if elems.size:
            k, c = np.unique(sks[_groups(elems)[1] > 1], return_counts=True)
            if k.size:
                yield _packed(1, k, np.zeros(k.size, np.int64), c, buckets)

    dealt = arrow_map(docs.select(F.col(ID).cast("long").alias(ID), TEXT), deal, _ROW)
    return _totals(arrow_map(_by_bucket(dealt, docs), count, _ROW), docs)


def _deal_sets(docs: DataFrame, chosen: DataFrame, n_chosen: int, mark: str | None) -> DataFrame:
    """The full sets of the chosen texts, dealt by hash; each hash carries its set's key and, if asked, a mark of its set."""
    buckets = _buckets(docs)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            elems, keys, marks = [], [], []
            for text, k, m in zip(strings(batch, TEXT), batch.column("sk").to_pylist(), batch.column("mark").to_pylist(), strict=True):
                s = shingle_set(text)
                if s.size and set_key(s) == k:
                    elems.append(s)
                    keys.append(k)
                    marks.append(m)
            if elems:
                sizes = [x.size for x in elems]
                marked = np.repeat(np.array(marks, np.uint8), sizes) if mark else None
                yield _dealt(2, np.concatenate(elems), np.repeat(np.array(keys, np.int64), sizes), marked, buckets, 8)

    side = chosen.select("sk", "rep", (F.col(mark) if mark else F.lit(0)).alias("mark"))
    return _by_bucket(arrow_map(_texts_of(docs, side, n_chosen).select(TEXT, "sk", "mark"), deal, _ROW), docs)


def _rarity(size: np.ndarray) -> np.ndarray:
    """0 for a hash of one set alone, then by doublings of the number of sets."""
    return np.floor(np.log2(size)).astype(np.int64)


def _stars(kind: int, elems: np.ndarray, sks: np.ndarray, buckets: int) -> pa.RecordBatch:
    """(a set, the smallest set it meets at a hash, at how many hashes)."""
    first, size = _groups(elems)
    at = np.flatnonzero((size > 1) & (first != np.arange(elems.size)))
    pair, c = np.unique(np.stack([sks[first[at]], sks[at]], axis=1), axis=0, return_counts=True)
    return _packed(kind, pair[:, 1], pair[:, 0], c, buckets)


def second_pass(docs: DataFrame, chosen: DataFrame, n_chosen: int) -> DataFrame:
    """kind 2: (sk, doc_id: rarity, n: shingles of that rarity); kind 3: (sk, doc_id: the smallest set met, n: how often)."""
    buckets = _buckets(docs)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, elems, sks, _ = _gathered(batches, 8)
        if not elems.size:
            return
        pair, c = np.unique(np.stack([sks, _rarity(_groups(elems)[1])], axis=1), axis=0, return_counts=True)
        yield _packed(2, pair[:, 0], pair[:, 1], c, buckets)
        yield _stars(3, elems, sks, buckets)

    return _totals(arrow_map(_deal_sets(docs, chosen, n_chosen, None), count, _ROW), docs)


def neighbour_pass(docs: DataFrame, chosen: DataFrame, n_chosen: int) -> DataFrame:
    """(a, b): sets that meet at a hash among the rarest quarter of both (``most`` is the rarity that quarter ends in)."""
    buckets = _buckets(docs)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, elems, sks, most = _gathered(batches, 8)
        if elems.size:
            near = _rarity(_groups(elems)[1]) <= most.astype(np.int64) - 1  # 0 marks sets that link with nothing
            yield _stars(4, elems[near], sks[near], buckets)

    return _totals(arrow_map(_deal_sets(docs, chosen, n_chosen, "most"), meet, _ROW), docs).select(F.col("doc_id").alias("a"), F.col("sk").alias("b"))


def tile_links(sets: list[np.ndarray], classes: list[int], blocks: list[int]) -> list[tuple[int, int]]:
    """Index pairs that link different classes, as many as join what is linked; sets of two blocks, if there are two, are compared across."""
    order = sorted(range(len(sets)), key=lambda i: sets[i].size)
    n = np.array([sets[i].size for i in order], np.int64)
    cls, blk = np.array([classes[i] for i in order]), np.array([blocks[i] for i in order])
    across = len(set(blocks)) > 1
    bits = max(64, 1 << (2 * int(n[-1]) - 1).bit_length()) if n.size else 64
    maps = np.zeros((len(order), min(bits, 1 << 14) // 64), np.uint64)
    for row, i in enumerate(order):
        h = sets[i] >> _U(17)
        np.bitwise_or.at(maps[row], (h // _U(64) % _U(maps.shape[1])).astype(np.int64), _U(1) << h % _U(64))
    out = []
    for row in range(len(order) - 1):
        end = int(np.searchsorted(n, n[row] * 4 // 3, side="right"))
        near = np.arange(row + 1, end)
        near = near[cls[near] != cls[row]]
        if across:
            near = near[blk[near] != blk[row]]
        if not near.size:
            continue
        need = -(-3 * (n[row] + n[near]) // 7)
        most = np.minimum(n[row] - np.bitwise_count(maps[row] & ~maps[near]).sum(axis=1, dtype=np.int64), n[near] - np.bitwise_count(maps[near] & ~maps[row]).sum(axis=1, dtype=np.int64))
        for j in near[most >= need].tolist():
            if cls[j] == cls[row]:
                continue
            a, b = sets[order[row]], sets[order[j]]
            shared = int((b[np.minimum(np.searchsorted(b, a), b.size - 1)] == a).sum())
            if 4 * shared >= 3 * (a.size + b.size - shared):
                out.append((order[row], order[j]))
                cls[cls == cls[j]] = cls[row]
    return out


def size_band(n: int) -> int:
    """Sets of 0.75 similarity or more lie in the same or in neighbouring bands."""
    return math.floor(math.log(n) / math.log(4 / 3) + 1e-9)


def tiles_of(key: int, n: int, members: int, bands: dict[int, int]) -> list[tuple[int, int]]:
    """(tile, block) of a set in a neighbourhood of ``members`` sets, ``bands`` of them by band. A small neighbourhood is one
    tile; in others, blocks of a band are compared with each other and with those of the next band.
    """
    if members <= TILE_SETS:
        return [(0, 0)]
    band = size_band(n)
    blocks = {b: -(-bands.get(b, 0) // TILE_SETS) for b in (band - 1, band, band + 1)}
    own = key % blocks[band]
    out = [(band << 42 | min(own, other) << 21 | max(own, other), own) for other in range(blocks[band])]
    out += [(1 << 62 | band << 42 | own << 21 | other, 0) for other in range(blocks[band + 1])]
    return out + [(1 << 62 | (band - 1) << 42 | other << 21 | own, 1) for other in range(blocks[band - 1])]


def tile_pass(docs: DataFrame, rest: DataFrame, n_rest: int) -> DataFrame:
    """Links (a, b) among the sets of ``rest`` (sk, rep, n, hood, class, members, bands), by tiles of a neighbourhood."""
    schema = "hood long, tile long, sk long, class long, block int, items binary"

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols: list[list] = [[] for _ in range(6)]
            for text, k, hood, cls, members, bands in zip(strings(batch, TEXT), *(batch.column(c).to_pylist() for c in ("sk", "hood", "class", "members", "bands")), strict=True):
                s = shingle_set(text)
                if set_key(s) != k:
                    continue
                data = s.tobytes()
                for tile, block in tiles_of(k, s.size, members, dict(bands)):
                    for col, x in zip(cols, (hood, tile, k, cls, block, data), strict=True):
                        col.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (*[pa.int64()] * 4, pa.int32(), pa.binary()), strict=True)], names=[c.split()[0] for c in schema.split(", ")])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True))
        for _, tile in groupby(rows, key=lambda r: r[:2]):
            members = list({r[2]: r for r in tile}.values())
            found = tile_links([np.frombuffer(r[5], np.uint64) for r in members], [r[3] for r in members], [r[4] for r in members])
            yield pa.RecordBatch.from_arrays([pa.array([members[i][2] for i, _ in found], pa.int64()), pa.array([members[j][2] for _, j in found], pa.int64())], names=["a", "b"])

    dealt = arrow_map(_texts_of(docs, rest, n_rest).select(TEXT, "sk", "hood", "class", "members", "bands"), deal, schema)
    return arrow_map(dealt.repartition("hood", "tile").sortWithinPartitions("hood", "tile"), compare, "a long, b long")


def jaccard_classes(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id): the smallest doc_id reachable by links of similarity 0.75 or more."""
    return keyed_classes(docs).drop("sk", "class")


def keyed_classes(docs: DataFrame) -> DataFrame:
    """As ``jaccard_classes``, with the key of each row's set (sk) and the smallest such key of its class (class)."""
    one = first_pass(docs)
    rows = one.where("kind = 0").select("doc_id", "sk", "n")
    sets = durable(rows.groupBy("sk").agg(F.min("doc_id").alias("rep"), F.min("n").alias("n")))
    met = one.where("kind = 1").groupBy("sk").agg(F.sum("n").alias("met"))
    need = F.floor(F.ceil(3 * F.col("n") / 4) / 8) + 1
    chosen = durable(sets.where("n > 0").join(met, "sk").where(F.col("met") >= need).select("sk", "rep", "n"))
    n_chosen = chosen.count()
    named = rows.where("n = 0").select(F.col("doc_id").alias(ID), F.lit(0).cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id"), "sk", F.col("sk").alias("class"))
    names = None
    if n_chosen:
        two = second_pass(docs, chosen, n_chosen)
        size = chosen.select("sk", "n")
        proof = two.where("kind = 3").groupBy(F.col("doc_id").alias("a"), F.col("sk").alias("b")).agg(F.sum("n").alias("shared"))
        links = (
            proof.join(size.withColumnsRenamed({"sk": "a", "n": "na"}), "a").join(size.withColumnsRenamed({"sk": "b", "n": "nb"}), "b").where(_linked(F.col("shared"), F.col("na"), F.col("nb"))).select("a", "b")
        )
        links = durable(links)
        classes = connected(links)
        # the rarity in which the rarest quarter (and one) of a set ends; 0 if that is shingles of its own alone
        up_to = F.sum("n").over(Window.partitionBy("sk").orderBy("rarity").rowsBetween(Window.unboundedPreceding, 0))
        steps = two.where("kind = 2").groupBy("sk", F.col("doc_id").alias("rarity")).agg(F.sum("n").alias("n")).select("sk", "rarity", up_to.alias("up_to"))
        ends = steps.join(size, "sk").where(F.col("up_to") >= F.col("n") - F.ceil(3 * F.col("n") / 4) + 1).groupBy("sk").agg(F.min("rarity").alias("end"))
        marked = chosen.join(ends, "sk").select("sk", "rep", "n", F.when(F.col("end") > 0, F.col("end") + 1).otherwise(0).cast("int").alias("most"))
        marked = durable(marked)
        able = marked.where("most > 0").select("sk", "rep", "n")
        hoods = connected(neighbour_pass(docs, marked, n_chosen))
        placed = able.join(hoods.select(F.col("node").alias("sk"), F.col("root").alias("hood")), "sk").join(classes.select(F.col("node").alias("sk"), F.col("root").alias("class")), "sk", "left")
        placed = durable(placed.withColumn("class", F.coalesce("class", "sk")))
        band = F.floor(F.log("n") / math.log(4 / 3) + 1e-9).cast("int")
        by_band = placed.groupBy("hood", band.alias("band")).agg(F.count(F.lit(1)).alias("members"), F.min("class").alias("lo"), F.max("class").alias("hi"))
        several = by_band.groupBy("hood").agg(F.sum("members").alias("members"), F.map_from_entries(F.collect_list(F.struct("band", "members"))).alias("bands"), F.min("lo").alias("lo"), F.max("hi").alias("hi")).where("lo < hi").select("hood", "members", "bands")
        rest = durable(placed.join(several, "hood"))
        n_rest = rest.count()
        if n_rest:
            classes = connected(links.union(tile_pass(docs, rest, n_rest)))
        linked = classes.join(sets.select(F.col("sk").alias("node"), "rep"), "node")
        names = durable(linked.join(linked.groupBy("root").agg(F.min("rep").alias("component")), "root").select(F.col("node").alias("sk"), F.col("root").alias("class"), "component"))
    full = rows.where("n > 0").join(sets.select("sk", "rep"), "sk")
    if names is not None:
        full = full.join(names, "sk", "left")
        # of a class whose rows all lack an id, ``component`` is null, and so are the ids of its sets
        component, cls = F.coalesce("component", "rep"), F.coalesce("class", "sk")
    else:
        component, cls = F.col("rep"), F.col("sk")
    return full.select(F.col("doc_id").alias(ID), F.col("n").cast("long").alias("n_shingles"), component.alias("component_id"), "sk", cls.alias("class")).union(named)


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """One row of each class of ``docs``, all columns: one of the smallest id (rows without an id come last) and, where that id
    stands with several texts of the class, of the smallest set key. Rows with an empty set are classes of their own and stay.

    Rows are told apart by id and set: an id that stands with unrelated texts loses none of them, and copies without an
    id go like others. Sets are made again only for ids that stand in several rows.
    """
    names = docs.columns
    plain = docs.toDF(*(f"c{i}" for i in range(len(names))))  # no name of the table can clash with one of these here
    id_col, text_col = f"c{names.index(ID)}", f"c{names.index(TEXT)}"
    classes = durable(keyed_classes(docs).select("doc_id", "n_shingles", "sk", "class"))
    filled = classes.where("n_shingles > 0")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("no"), "doc_id", "sk")).alias("m")
    lead = durable(filled.groupBy("class").agg(first, F.count(F.lit(1)).alias("members")).select("class", F.col("m.doc_id").alias("lead_id"), F.col("m.sk").alias("lead_set"), "members"))
    several = durable(classes.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL").select(F.col("doc_id").alias("several_id")))
    # fewer than MOST_BROADCAST classes can have more members than this, so their rows needn't meet in one task
    most = max(HOT_CLASS, (lead.agg(F.sum("members")).first()[0] or 0) // max(1, MOST_BROADCAST))
    hot = F.broadcast(lead.where(F.col("members") > most).select("class", "lead_id"))
    cool = lead.where(F.col("members").between(2, most)).select("class", "lead_id")
    led = filled.join(hot, "class").select("doc_id", "lead_id").union(filled.join(hot, "class", "left_anti").join(cool, "class").select("doc_id", "lead_id"))
    gone = durable(led.where(~F.col("doc_id").eqNullSafe(F.col("lead_id"))).select(F.col("doc_id").alias("gone_id")).where("gone_id IS NOT NULL").distinct())
    n_several, n_gone = several.count(), gone.count()
    side = lambda df, n: F.broadcast(df) if n <= MOST_BROADCAST else df
    key = F.col(id_col).cast("long")
    if not n_several:
        return plain.join(side(gone, n_gone), key == F.col("gone_id"), "left_anti").toDF(*names)
    again = key.eqNullSafe(F.col("several_id"))
    once = plain.join(side(several, n_several), again, "left_anti").join(side(gone, n_gone), key == F.col("gone_id"), "left_anti")

    def tell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set(t) for t in strings(batch, text_col)]
            keys = pa.array([set_key(s) if s.size else None for s in sets], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns, keys], names=[*batch.schema.names, "set_key"])

    told = arrow_map(plain.join(side(several, n_several), again, "left_semi"), tell, StructType([*plain.schema.fields, StructField("set_key", LongType())]))
    chosen = durable(lead.join(several, F.col("lead_id").eqNullSafe(F.col("several_id")), "left_semi").select("lead_id", "lead_set"))
    of_chosen = key.eqNullSafe(F.col("lead_id")) & (F.col("set_key") == F.col("lead_set"))
    kept = told.join(side(chosen, chosen.count()), of_chosen, "left_semi").dropDuplicates([id_col, "set_key"])
    return once.unionByName(told.where("set_key IS NULL").unionByName(kept).drop("set_key")).toDF(*names)
