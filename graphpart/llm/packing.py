"""Lexical retrieval packing: each seed document's window is filled by its unused nearest neighbours from a BM25 index.

The index lies in shards of bounded size, and related documents share a shard. Document frequencies and the mean length
are counted over the whole corpus first (words hashed to SLOTS slots, so the table has a fixed size). Documents are then
laid on one line by content: leaf of k-means over sketches of their weighted words (learnt from a bounded sample), place along the main axis within
the leaf, hash among equals. The line is cut into shards of about SHARD_WEIGHT, so a group of copies of any size is cut
as well, and a document's shard depends on its own text and on corpus statistics, not on the layout of the table.

In a shard, whole windows are cut from documents longer than one; then the longest unused rest becomes the seed, all its
terms are scored, and its unused neighbours follow best first, the last one cut to the room left. The last window of a
shard is cut into powers of two, which need no padding. Neighbours in other shards are lost to a seed:
``shared_neighbours`` measures how many, and the README says how many on the given tables.

Weights are whole numbers of 1 / UNIT, so their sums are exact in any order. The driver holds compressed counts by slot and
the line, never texts, sketches, ids of tokens or postings. Time grows in proportion to the corpus.

Edge cases: a null or empty text is the closing id alone; texts of any length are cut freely; repeated rows are packed
as often as they stand there; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache
from hashlib import blake2b
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.llm.ann import balanced_centroids
from graphpart.llm.common import ID, TEXT, arrow_map, durable, strings
from graphpart.llm.tokens import WordVocabulary, word_vocabulary

WINDOW, CLOSING = 4096, 2
SLOTS, CHUNK = 1 << 20, 1 << 12
SHARD_WEIGHT, DOC_WEIGHT = 2_000_000, 200  # tokens of a shard; what a document weighs besides its tokens
SAMPLE, MOST_LEAVES = 12_000, 2048
DIMS, BINS = 128, 64
FEW = 6  # tokens of a word that are hashed place by place
OFTEN = 8  # terms in over 1 / OFTEN of a shard's documents are added up as dense rows
REMEMBERED = 200_000
K1, B = 1.2, 0.75
UNIT = float(1 << 20)
Piece = tuple[int, int, int]  # document, start, length


def idf_of(df: np.ndarray, n: int) -> np.ndarray:
    return np.log(1 + (n - df + 0.5) / (df + 0.5))


def term_weights(tf: np.ndarray, idf: np.ndarray, sizes: np.ndarray, mean: float) -> np.ndarray:
    """BM25 of a term in a document, in whole units."""
    return np.rint(UNIT * idf * tf * (K1 + 1) / (tf + K1 * (1 - B + B * sizes / max(1.0, mean))))


class Bm25Index:
    """Postings of some documents, weighed by frequencies in the whole corpus. ``docs`` are arrays of terms (numbers of a table's places), repeats counted."""

    def __init__(self, docs: list[np.ndarray], idf: np.ndarray | None = None, mean: float | None = None) -> None:
        """``idf`` by term; counted here, like ``mean``, if the documents are the whole corpus."""
        sizes = np.array([d.size for d in docs], np.int64)
        flat = np.concatenate(docs) if docs else np.zeros(0, np.int64)
        met = np.zeros(int(flat.max(initial=-1)) + 1, bool)
        met[flat] = True
        names, number = np.flatnonzero(met), (np.cumsum(met) - 1)[flat]
        bits = names.size.bit_length()
        key = np.repeat(np.arange(len(docs)), sizes) << bits | number
        key, tf = np.unique(key.astype(np.uint32) if len(docs) << bits <= 1 << 32 else key, return_counts=True)
        key = key.astype(np.int64)
        doc, term = key >> bits, key & (1 << bits) - 1
        of_term = idf_of(np.bincount(term, minlength=names.size), len(docs)) if idf is None else idf[names]
        weight = term_weights(tf, of_term[term], sizes[doc], float(sizes.mean()) if mean is None and len(docs) else mean or 1.0)
        self.terms = np.split(term, np.searchsorted(doc, np.arange(1, len(docs)))) if docs else []
        bits = key.size.bit_length()
        order = np.sort(term << bits | np.arange(key.size)) & (1 << bits) - 1  # by term, then document; faster than a stable argsort
        self._lay(np.bincount(term, minlength=names.size), doc[order], weight[order], np.arange(len(docs)))

    def _lay(self, df: np.ndarray, doc: np.ndarray, weight: np.ndarray, number: np.ndarray) -> None:
        self.df, self.doc, self.weight, self.number = df, doc, weight, number
        self.at = np.r_[0, np.cumsum(df)]
        often = np.flatnonzero(df * OFTEN > number.size)
        self.row = np.full(df.size, -1)
        self.row[often] = np.arange(often.size)
        self.dense = np.zeros((often.size, number.size))
        for row, t in enumerate(often.tolist()):
            some = slice(self.at[t], self.at[t + 1])
            self.dense[row, doc[some]] = weight[some]

    def forget(self, alive: np.ndarray) -> None:
        """Leave out the documents that aren't alive."""
        keep, live = alive[self.number][self.doc], alive[self.number]
        df = np.diff(np.r_[0, np.cumsum(keep)][self.at])
        self._lay(df, (np.cumsum(live) - 1)[self.doc[keep]], self.weight[keep], self.number[live])

    def scores(self, doc: int) -> np.ndarray:
        """BM25 for all terms of one document, by place in ``number``."""
        t = self.terms[doc]
        row = self.row[t]
        out = self.dense[row[row >= 0]].sum(axis=0)
        t = t[row < 0]
        size = self.df[t]
        end = np.cumsum(size)
        if t.size and end[-1]:
            at = np.repeat(self.at[t] - (end - size), size) + np.arange(int(end[-1]))
            out = out + np.bincount(self.doc[at], self.weight[at], self.number.size)
        return out

    def nearest(self, doc: int, alive: np.ndarray, first: int = 64) -> Iterator[int]:
        """Alive documents that share a term, best first, ties to the smaller number; the ``first`` are told before the rest is sorted."""
        score = self.scores(doc)
        some = np.flatnonzero((score > 0) & alive[self.number] & (self.number != doc))
        value = score[some]
        best = np.ones(some.size, bool)
        if some.size > 2 * first:
            best = value >= np.partition(value, some.size - first)[some.size - first]
        for part in (best, ~best):
            at, v = some[part], value[part]
            yield from self.number[at[np.lexsort((at, -v))]].tolist()


class Windows:
    """The rests of documents, and the windows filled from them."""

    def __init__(self, lengths: np.ndarray, window: int) -> None:
        self.start = lengths // window * window
        self.left = lengths - self.start
        self.window = window
        self.order = np.argsort(-self.left, kind="stable")
        self.at = 0

    def longest(self) -> int | None:
        """The longest unused rest."""
        while self.at < self.order.size and not self.left[self.order[self.at]]:
            self.at += 1
        return int(self.order[self.at]) if self.at < self.order.size else None

    def _take(self, d: int, most: int) -> Piece:
        n = min(most, int(self.left[d]))
        piece = (d, int(self.start[d]), n)
        self.start[d] += n
        self.left[d] -= n
        return piece

    def fill(self, seed: int, near: Iterator[int]) -> tuple[list[Piece], int]:
        """Pieces of the seed's window, and the room left: the nearest first, then the longest rests."""
        pieces = [self._take(seed, self.window)]
        room = self.window - pieces[0][2]
        for d in near if room else ():
            pieces.append(self._take(d, room))
            room -= pieces[-1][2]
            if not room:
                break
        while room and (d := self.longest()) is not None:
            pieces.append(self._take(d, room))
            room -= pieces[-1][2]
        return pieces, room


def _whole_windows(lengths: np.ndarray, window: int) -> Iterator[list[Piece]]:
    for d in np.flatnonzero(lengths >= window).tolist():
        for s in range(0, int(lengths[d]) // window * window, window):
            yield [(d, s, window)]


def pack_shard(lengths: np.ndarray, terms: list[np.ndarray], window: int = WINDOW, idf: np.ndarray | None = None, mean: float | None = None) -> list[list[Piece]]:
    """Sequences of pieces; every id of every document in one piece. One seed after the other over one index."""
    lengths = np.asarray(lengths, np.int64)
    out = list(_whole_windows(lengths, window))
    index, w = Bm25Index(terms, idf, mean), Windows(lengths, window)
    last: list[Piece] = []
    while (seed := w.longest()) is not None:
        alive = w.left > 0
        if alive.sum() * 2 < index.number.size:
            index.forget(alive)
        pieces, room = w.fill(seed, index.nearest(seed, alive))
        if room:
            last = pieces
        else:
            out.append(pieces)
    return out + powers_of_two(last)


def powers_of_two(pieces: list[Piece]) -> list[list[Piece]]:
    """The pieces dealt to sequences whose lengths are the powers of two of their sum, largest first."""
    total, out, k, used = sum(p[2] for p in pieces), [], 0, 0
    for bit in range(total.bit_length() - 1, -1, -1):
        if not total >> bit & 1:
            continue
        need, row = 1 << bit, []
        while need:
            d, s, n = pieces[k]
            take = min(need, n - used)
            row.append((d, s + used, take))
            need -= take
            used += take
            if used == n:
                k, used = k + 1, 0
        out.append(row)
    return out


# -- words of token sequences, by slot


def _word_ends(path: str) -> np.ndarray:
    return word_vocabulary(path).ends


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
    return x ^ (x >> np.uint64(31))


_OF_ID = _mixed(np.arange(1 << 16, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(1))
_OF_PLACE = _mixed(np.arange(1 << 8, dtype=np.uint64) + np.uint64(77)) | np.uint64(1)


def word_slots(ids: np.ndarray, sizes: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, slot) of each word of documents whose ids lie one after the other, the closing id last."""
    if not ids.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    last = np.cumsum(sizes) - 1
    stop = ends[ids]
    stop[last] = True
    stop[last[sizes > 1] - 1] = True
    end = np.flatnonzero(stop)
    closing = np.searchsorted(end, last)  # the closing id is no word
    words = np.diff(np.r_[-1, closing]) - 1
    at, end = np.delete(np.r_[0, end[:-1] + 1], closing), np.delete(end, closing)
    x = _OF_ID[ids[at]] * _OF_PLACE[0]
    longer = np.flatnonzero(end > at)
    for place in range(1, FEW):
        x[longer] += _OF_ID[ids[at[longer] + place]] * _OF_PLACE[place]
        longer = longer[end[longer] > at[longer] + place]
    if longer.size:
        begin, n = at[longer] + FEW, end[longer] + 1 - at[longer] - FEW
        first = np.cumsum(n) - n
        place = np.arange(int(n.sum())) - np.repeat(first, n)
        x[longer] += np.add.reduceat(_OF_ID[ids[np.repeat(begin, n) + place]] * _OF_PLACE[np.minimum(place + FEW, 255)], first)
    return np.repeat(np.arange(sizes.size), words), (_mixed(x) >> np.uint64(64 - SLOTS.bit_length() + 1)).astype(np.int64)


def term_counts(doc: np.ndarray, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, slot, how often), by document, then slot."""
    bits = SLOTS.bit_length() - 1
    key = doc << bits | slot
    key, tf = np.unique(key.astype(np.uint32) if not doc.size or doc[-1] < 1 << (32 - bits) else key, return_counts=True)
    key = key.astype(np.int64)
    return key >> bits, key & (SLOTS - 1), tf


def packed_counts(df: np.ndarray) -> dict[int, bytes]:
    """The chunks of counts by slot that aren't all 0, compressed."""
    return {c: pa.compress(df[c * CHUNK : (c + 1) * CHUNK].tobytes(), codec="zstd", asbytes=True) for c in np.flatnonzero(df.reshape(-1, CHUNK).any(axis=1)).tolist()}


def unpacked_counts(chunk: bytes) -> np.ndarray:
    return np.frombuffer(pa.decompress(chunk, decompressed_size=8 * CHUNK, codec="zstd", asbytes=True), np.int64)


@dataclass
class Frequencies:
    """Documents by slot, of ``n``. They travel compressed; a process that asks for ``idf`` works it out once."""

    chunks: dict[int, bytes]
    n: int

    @cached_property
    def idf(self) -> np.ndarray:
        out = np.tile(idf_of(np.zeros(CHUNK, np.int64), self.n), SLOTS // CHUNK)
        for c, chunk in self.chunks.items():
            out[c * CHUNK : (c + 1) * CHUNK] = idf_of(unpacked_counts(chunk), self.n)
        return out


# -- the line of documents


@dataclass
class Line:
    """Where documents lie: centroids of leaves in their order, and the main axis of what they leave over."""

    centroids: np.ndarray
    axis: np.ndarray
    spread: float

    def cells(self, sketches: np.ndarray) -> np.ndarray:
        leaf, along = np.zeros(len(sketches), np.int64), np.zeros(len(sketches))
        for lo in range(0, len(sketches), 512):
            s = sketches[lo : lo + 512]
            at = np.round((self.centroids**2).sum(axis=1) - 2 * s @ self.centroids.T, 9).argmin(axis=1)
            leaf[lo : lo + 512], along[lo : lo + 512] = at, (s - self.centroids[at]) @ self.axis
        place = np.floor(BINS / 2 * (1 + np.round(along / (3 * self.spread), 6)))
        return leaf * BINS + np.clip(place, 0, BINS - 1).astype(np.int64)


@lru_cache(maxsize=1)
def _places() -> list[tuple[np.ndarray, np.ndarray]]:
    """For each of the two salts: the place of every slot in a sketch, and its sign."""
    out = []
    for salt in (1, 2):
        h = _mixed((np.arange(SLOTS) * 2 + salt).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        out.append((((h >> np.uint64(40)) % np.uint64(DIMS)).astype(np.int16), np.where(h & np.uint64(1), 1, -1).astype(np.int8)))
    return out


def sketch(doc: np.ndarray, slot: np.ndarray, tf: np.ndarray, n: int, idf: np.ndarray) -> np.ndarray:
    """Weighted terms of n documents, each added with a sign to two of DIMS numbers; of length one."""
    value = idf[slot] * tf / (tf + K1)
    out = np.zeros(n * DIMS)
    for place, sign in _places():
        out += np.bincount(doc * DIMS + place[slot], sign[slot] * value, n * DIMS)
    out = out.reshape(n, DIMS)
    return out / np.maximum(1e-12, np.sqrt((out * out).sum(axis=1)))[:, None]


def _fit_line(sample: np.ndarray, leaves: int) -> Line:
    """Leaves by balanced k-means, laid along the main axis of their centroids so that near leaves tend to be neighbours."""
    c = balanced_centroids(sample, max(1, min(leaves, MOST_LEAVES, len(sample))))
    main = np.linalg.svd(c - c.mean(axis=0), full_matrices=False)[2][0] if len(c) > 1 else np.eye(DIMS)[0]
    c = c[np.argsort(np.round(c @ main, 9), kind="stable")]
    left = sample - c[((c**2).sum(axis=1) - 2 * sample @ c.T).argmin(axis=1)]
    axis = np.linalg.svd(left, full_matrices=False)[2][0] if len(sample) > 1 else np.eye(DIMS)[0]
    axis = axis * np.sign(axis[np.abs(axis).argmax()])
    return Line(c, axis, max(1e-9, float((left @ axis).std())))


def _encoded(batch: pa.RecordBatch, vocabulary: WordVocabulary) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Texts, ids of all tokens, and how many each text has, the closing id included."""
    texts = strings(batch, TEXT)
    tokens, sizes = [np.zeros(0, np.uint16)], [np.zeros(0, np.int64)]
    for numbers, counts in vocabulary.numbers_of(texts):
        end = np.cumsum(counts)
        numbers = np.insert(numbers, end, vocabulary[(CLOSING,)])
        tokens.append(vocabulary.ids(numbers))
        sizes.append(np.diff(np.r_[0, np.cumsum(vocabulary.sizes()[numbers])[end + np.arange(end.size)]]))
    return texts, np.concatenate(tokens), np.concatenate(sizes)


def _learn(docs: DataFrame, path: str, n: int, step: int) -> tuple[Line, Frequencies]:
    """The line, and the frequencies that its sketches are weighed by, from the SAMPLE documents of the smallest hashes."""
    below = min(2**63 - 1, int(-(2**63) + 2**64 * 1.3 * SAMPLE / n))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, ends = word_vocabulary(path), _word_ends(path)
        for batch in batches:
            _, ids, sizes = _encoded(batch, vocabulary)
            doc, slot, tf = term_counts(*word_slots(ids, sizes, ends))
            at = np.searchsorted(doc, np.arange(sizes.size + 1)).tolist()
            terms = [slot[x:y].astype("<i4").tobytes() for x, y in zip(at[:-1], at[1:], strict=True)]
            counts = [np.minimum(tf[x:y], 65535).astype("<u2").tobytes() for x, y in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("_hash"), pa.array(sizes), pa.array(terms, pa.binary()), pa.array(counts, pa.binary())], names=["hash", "size", "terms", "counts"])

    hashed = docs.select(F.xxhash64(ID, TEXT).alias("_hash"), TEXT).where(F.col("_hash") <= below)
    few = durable(arrow_map(hashed, read, "hash long, size long, terms binary, counts binary").orderBy("hash", "terms").limit(SAMPLE))
    few = few.coalesce(1)  # the one task of its limit; the driver gets counts and the line alone

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, total, tokens = np.zeros(SLOTS, np.int64), 0, 0
        for batch in batches:
            total += batch.num_rows
            tokens += sum(batch.column("size").to_pylist())
            for terms in batch.column("terms").to_pylist():
                df[np.frombuffer(terms, "<i4")] += 1
        chunks = packed_counts(df)
        rows = [(-1, total, None), (-2, tokens, None), *((c, None, data) for c, data in chunks.items())]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), kind) for c, kind in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.binary()), strict=True)], names=["cell", "total", "data"])

    counted = {r["cell"]: r for r in arrow_map(few.select("size", "terms"), count, "cell long, total long, data binary").collect()}  # at most SLOTS counts, compressed
    total, tokens = (counted.pop(c)["total"] if c in counted else 0 for c in (-1, -2))
    rough = Frequencies({c: bytes(r["data"]) for c, r in counted.items()}, total)
    sent = docs.sparkSession.sparkContext.broadcast(rough)
    leaves = int((tokens / max(1, total) + DOC_WEIGHT) * n // step) + 1

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        drawn: list[tuple[int, bytes]] = []  # at most SAMPLE rows of 8 * DIMS bytes
        for batch in batches:
            terms, counts = ([np.frombuffer(x, kind) for x in batch.column(c).to_pylist()] for c, kind in (("terms", "<i4"), ("counts", "<u2")))
            doc = np.repeat(np.arange(len(terms)), [t.size for t in terms])
            made = sketch(doc, np.concatenate(terms).astype(np.int64), np.concatenate(counts).astype(np.int64), len(terms), sent.value.idf)
            drawn += zip(batch.column("hash").to_pylist(), (x.tobytes() for x in made), strict=True)
        sample = np.frombuffer(b"".join(x for _, x in sorted(drawn)), np.float64).reshape(-1, DIMS)
        made = _fit_line(sample if len(sample) else np.zeros((1, DIMS)), leaves)
        yield pa.RecordBatch.from_arrays([pa.array([made.centroids.tobytes()]), pa.array([made.axis.tobytes()]), pa.array([made.spread])], names=["centroids", "axis", "spread"])

    r = arrow_map(few.select("hash", "terms", "counts"), fit, "centroids binary, axis binary, spread double").first()  # at most MOST_LEAVES centroids
    line = Line(np.frombuffer(r["centroids"]).reshape(-1, DIMS), np.frombuffer(r["axis"]), r["spread"]) if r else _fit_line(np.zeros((1, DIMS)), leaves)
    return line, rough


_SCHEMA = "tie long, size long, words long, cell long, data binary"


def _read(docs: DataFrame, path: str, line, rough) -> DataFrame:
    """A row for each document: ``tie`` (a hash of id, text, and of how often the task met both before), how many tokens and
    words, its cell on the line, token ids. Cells below 0 are chunks of a task's counts of documents by slot.
    """
    kind = docs.schema[ID].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, ends = word_vocabulary(path), _word_ends(path)
        met: dict[bytes, int] = {}
        df, of_id = np.zeros(SLOTS, np.int64), None
        for batch in batches:
            of_id = batch.column(0).type
            texts, ids, sizes = _encoded(batch, vocabulary)
            ties = []
            for key, text in zip(batch.column(0).to_pylist(), texts, strict=True):
                name = blake2b(f"{key}\0{text}".encode("utf-8", "surrogatepass"), digest_size=8).digest()
                again = met[name] = met.get(name, -1) + 1
                ties.append(int.from_bytes(blake2b(name + again.to_bytes(8, "little"), digest_size=8).digest() if again else name, "little", signed=True))
            if len(met) > REMEMBERED:
                met.clear()
            doc, slot = word_slots(ids, sizes, ends)
            words = np.bincount(doc, minlength=sizes.size)
            doc, slot, tf = term_counts(doc, slot)
            df += np.bincount(slot, minlength=SLOTS) if slot.size > SLOTS // 8 else 0
            if slot.size <= SLOTS // 8:
                np.add.at(df, slot, 1)
            cells = line.value.cells(sketch(doc, slot, tf, sizes.size, rough.value.idf))
            at = pa.array(np.r_[0, np.cumsum(2 * sizes)]).cast(pa.int32())  # refuses what doesn't fit
            data = pa.Array.from_buffers(pa.binary(), sizes.size, [None, at.buffers()[1], pa.py_buffer(ids.astype("<u2"))])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ties, pa.int64()), pa.array(sizes), pa.array(words, pa.int64()), pa.array(cells), data], names=_NAMES)
        if of_id is not None:
            chunks = packed_counts(df)
            none = pa.nulls(len(chunks), pa.int64())
            cells = pa.array([-1 - c for c in chunks], pa.int64())
            yield pa.RecordBatch.from_arrays([pa.nulls(len(chunks), of_id), none, none, none, cells, pa.array(list(chunks.values()), pa.binary())], names=_NAMES)

    return arrow_map(docs.select(ID, TEXT), run, f"{ID} {kind.simpleString()}, {_SCHEMA}")


_NAMES = [ID, *(c.split()[0] for c in _SCHEMA.split(", "))]


def _frequencies(read: DataFrame, n: int) -> Frequencies:
    """Documents by slot, over all rows: the tasks' chunks summed by other tasks."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for c, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                total[c] = total.get(c, 0) + unpacked_counts(data)
        sums = [packed_counts(x)[0] for x in total.values()]
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array(sums, pa.binary())], names=["cell", "data"])

    summed = arrow_map(read.where("cell < 0").select("cell", "data").repartition("cell"), add, "cell long, data binary").collect()  # at most SLOTS counts, compressed
    return Frequencies({-1 - r["cell"]: bytes(r["data"]) for r in summed}, n)


def _dealt(docs: DataFrame, path: str, step: int) -> tuple[DataFrame, int, object, float] | None:
    """Rows with their shard, how many shards there are, and what weighs terms: frequencies by slot (broadcast) and the mean length."""
    sc = docs.sparkSession.sparkContext
    n = docs.count()
    if not n:
        return None
    line, rough = _learn(docs, path, n, step)
    read = durable(_read(docs, path, sc.broadcast(line), sc.broadcast(rough)))  # at most MOST_LEAVES centroids; compressed counts
    idf = sc.broadcast(_frequencies(read, n))
    rows = read.where("cell >= 0")
    by_cell = rows.groupBy("cell").agg(F.sum(F.col("size") + DOC_WEIGHT).alias("weight"), F.sum("words").alias("words")).orderBy("cell").collect()  # at most MOST_LEAVES * BINS rows
    places, at = [], 0
    for r in by_cell:
        places.append((r["cell"], at, r["weight"]))
        at += r["weight"]
    cells = F.broadcast(docs.sparkSession.createDataFrame(places, "cell long, before long, weight long"))
    # where a hash lies between the least and the greatest, as a share of its cell's weight
    along = F.col("before") + (F.col("tie").cast("double") / F.lit(2.0**64) + 0.5) * F.col("weight")
    dealt = rows.join(cells, "cell").select(F.floor(along / step).cast("long").alias("shard"), ID, "tie", "size", "data")
    return dealt, int(at // step) + 1, idf, sum(r["words"] for r in by_cell) / n


def _by_shard(batches: Iterator[pa.RecordBatch], path: str) -> Iterator[tuple[int, list, np.ndarray, np.ndarray, list[np.ndarray]]]:
    """(shard, document ids, lengths, token ids, slots of each document) of each shard, rows sorted by shard."""
    rows = (r for b in batches for r in zip(*(b.column(c).to_pylist() for c in ("shard", ID, "size", "data")), strict=True))
    for shard, group in groupby(rows, key=lambda r: r[0]):
        _, keys, sizes, tokens = zip(*group, strict=True)
        lengths, flat = np.array(sizes, np.int64), np.frombuffer(b"".join(tokens), "<u2")
        doc, slot = word_slots(flat, lengths, _word_ends(path))
        yield shard, list(keys), lengths, flat, np.split(slot, np.searchsorted(doc, np.arange(1, lengths.size)))


def _to_shards(rows: DataFrame, shards: int) -> DataFrame:
    tasks = min(shards, max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), 4 * rows.sparkSession.sparkContext.defaultParallelism, shards // 8))
    return rows.repartition(tasks, "shard").sortWithinPartitions("shard", "tie", "size")


def pack_documents(docs: DataFrame, path: str, window: int = WINDOW, shard_weight: int = SHARD_WEIGHT) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset), a row for each piece."""
    kind = docs.schema[ID].dataType.simpleString()
    schema = f"{ID} {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    dealt = _dealt(docs, path, shard_weight)
    if dealt is None:
        return docs.sparkSession.createDataFrame([], schema)
    rows, shards, idf, mean = dealt

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = None

        def watched() -> Iterator[pa.RecordBatch]:
            nonlocal kind
            for b in batches:
                kind = b.column(ID).type
                yield b

        for shard, keys, lengths, flat, terms in _by_shard(watched(), path):
            first, wide = np.cumsum(lengths) - lengths, flat.astype("<u4")
            out: list[tuple] = []
            for number, pieces in enumerate(pack_shard(lengths, terms, window, idf.value.idf, mean)):
                offset = 0
                for d, start, n in pieces:
                    at = int(first[d]) + start
                    out.append((keys[d], start, n, zlib.crc32(wide[at : at + n]), int(lengths[d]), shard << 32 | number, offset))
                    offset += n
            cols = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(list(c), kind if i == 0 else pa.int64()) for i, c in enumerate(cols)], names=[c.split()[0] for c in schema.split(", ")])

    return arrow_map(_to_shards(rows, shards), pack, schema)


def shared_neighbours(docs: DataFrame, path: str, every: int = 50, most: int = 10, shard_weight: int = SHARD_WEIGHT) -> tuple[float, float]:
    """What shards keep of the best ``most`` BM25 neighbours over the whole corpus, for every ``every``-th document by hash:
    the share of them that lie in the document's own shard, and the scores of the best there against theirs.

    A measurement for corpora that fit one task: all terms are gathered.
    """
    dealt = _dealt(docs, path, shard_weight)
    if dealt is None:
        return 1.0, 1.0
    rows, _, idf, mean = dealt
    made = rows.orderBy("tie", "size").collect()
    lengths = np.array([r["size"] for r in made], np.int64)
    doc, slot = word_slots(np.frombuffer(b"".join(bytes(r["data"]) for r in made), "<u2"), lengths, _word_ends(path))
    index = Bm25Index(np.split(slot, np.searchsorted(doc, np.arange(1, lengths.size))), idf.value.idf, mean)
    shard = np.array([r["shard"] for r in made])
    alive = np.ones(lengths.size, bool)
    hits, kept = [], []
    for d in range(0, lengths.size, every):
        near, score = np.fromiter(index.nearest(d, alive), np.int64), index.scores(d)
        if near.size:
            hits.append((shard[near[:most]] == shard[d]).mean())
            kept.append(score[near[shard[near] == shard[d]][:most]].sum() / score[near[:most]].sum())
    return (float(np.mean(hits)), float(np.mean(kept))) if hits else (1.0, 1.0)
