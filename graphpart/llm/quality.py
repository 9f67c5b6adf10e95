"""Quality classifier: hashed word n-gram logistic regression, trained by follow-the-regularised-leader, scored as sparse dot products.

Terms of a text: its words, pairs of neighbouring words, the shapes of words (letters, digits and other characters in
collapsed runs), pairs of shapes, and a mark where a word repeats the one before. Each is hashed to one of 2^18 slots;
a slot's value is its share of the text's terms. Every text is scored whole.

Edge cases: null and empty texts get the score of the bias alone; a table without labelled rows gives the model that
scores 0.5 everywhere; repeated rows score alike; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphpart.llm.common import ID, TEXT, arrow_map, bounded_sample, give_back, remainder, strings

BITS = 18
MASK = (1 << BITS) - 1
GAIN = 16.0
MAX_TRAIN_DOCS, MAX_TRAIN_CHARS = 6000, 30_000
CACHE_WORDS = 250_000


def shape_of(word: str) -> str:
    out: list[str] = []
    for c in word:
        k = "A" if c.isupper() else "a" if c.isalpha() else "0" if c.isdigit() else c
        if not out or out[-1] != k:
            out.append(k)
    return "".join(out[:24])


class TermHasher(dict):
    """Word -> number packing the hashes of the word and of its shape; bounded, refilled when full."""

    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        packed = zlib.crc32(word.encode()) << 31 | zlib.crc32(shape_of(word).encode(), 7) >> 1
        self[word] = packed
        return packed

    def slots(self, text: str) -> np.ndarray:
        words = text.split()
        if not words:
            return np.empty(0, np.int64)
        packed = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        word, shape = packed >> 31, packed & 0x7FFFFFFF
        parts = [word * 3, shape * 5 + 1, word[:-1] * 7919 + word[1:] * 104729 + 2, shape[:-1] * 6151 + shape[1:] * 24593 + 3, np.full(int((word[1:] == word[:-1]).sum()), 4)]
        h = np.concatenate(parts).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return (h >> np.uint64(64 - BITS)).astype(np.int64)


class FtrlModel:
    """Per-coordinate FTRL-proximal for logistic loss; ``weights`` and ``bias`` are what scoring needs."""

    def __init__(self, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.5) -> None:
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros(1 << BITS), np.zeros(1 << BITS)
        self.bias, self.bias_n = 0.0, 0.0

    def _weights(self, at: np.ndarray) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        w = -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def update(self, at: np.ndarray, x: np.ndarray, y: int) -> float:
        w = self._weights(at)
        p = sigmoid(self.bias + float(w @ x))
        g = (p - y) * x
        sigma = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        self.z[at] += g - sigma * w
        self.n[at] += g * g
        self.bias_n += (p - y) ** 2
        self.bias -= 0.5 * (p - y) / (1 + self.bias_n**0.5)
        return p

    @property
    def weights(self) -> np.ndarray:
        return self._weights(np.arange(1 << BITS)).astype(np.float32)


def sigmoid(x: float) -> float:
    return 1 / (1 + float(np.exp(-min(60.0, max(-60.0, x)))))


def train(pairs: list[tuple[str, int]], epochs: int = 3, seed: int = 7) -> tuple[np.ndarray, float]:
    """Weights and bias from (text, 0 or 1)."""
    model, hasher, rows = FtrlModel(), TermHasher(), []
    for text, y in pairs:
        at, c = np.unique(hasher.slots(text), return_counts=True)
        rows.append((at.astype(np.int32), c.astype(np.min_scalar_type(c.max(initial=0))), int(y)))  # as small as they fit: the driver holds all rows
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for i in rng.permutation(len(rows)):
            at, c, y = rows[i]
            c = c.astype(np.int64)
            model.update(at.astype(np.int64), GAIN * c / max(1, c.sum()), y)
    return model.weights, model.bias


def fit_quality(docs: DataFrame, labels: DataFrame, train_only: bool = True, max_docs: int = MAX_TRAIN_DOCS, max_chars: int = MAX_TRAIN_CHARS) -> tuple[np.ndarray, float]:
    """Train on a bounded sample of labelled rows; with ``train_only``, rows held out (crc32 of the id, mod 5, is 0) are never seen."""
    rows = labels.select(ID, "quality")
    model = train(bounded_sample(docs, rows.where(remainder(ID, 5) != 0) if train_only else rows, "quality", max_docs, max_chars))
    give_back()
    return model


_HASHER = TermHasher()


def scores(texts: list[str], weights: np.ndarray, bias: float) -> np.ndarray:
    """Sparse dot product of each text's terms and the weights, through the logistic function; 0 to 1."""
    out = np.empty(len(texts))
    for i, text in enumerate(texts):
        at = _HASHER.slots(text)
        out[i] = bias + (GAIN * float(weights[at].sum(dtype=np.float64)) / at.size if at.size else 0.0)
    return 1 / (1 + np.exp(-np.clip(out, -60, 60)))


def score_quality(docs: DataFrame, model: tuple[np.ndarray, float], threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row; the model (1 MB, fixed) goes with the tasks."""
    weights, bias = docs.sparkSession.sparkContext.broadcast(model[0]), model[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = scores(strings(batch, TEXT), weights.value, bias)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=[ID, "held_out", "score", "predicted"])

    rows = docs.select(ID, (remainder(ID, 5) == 0).alias("held_out"), TEXT)
    return arrow_map(rows, run, f"{ID} {docs.schema[ID].dataType.simpleString()}, held_out boolean, score double, predicted int")


def keep_quality(docs: DataFrame, model: tuple[np.ndarray, float], threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs``, all columns, whose text scores at least ``threshold``."""
    weights, bias = docs.sparkSession.sparkContext.broadcast(model[0]), model[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(scores(strings(batch, TEXT), weights.value, bias) >= threshold))

    return arrow_map(docs, run, docs.schema)


def quality_report(scored: DataFrame, labels: DataFrame) -> DataFrame:
    """Confusion counts by held_out, for rows that have a label."""
    return scored.join(labels.select(ID, "quality"), ID).groupBy("held_out", "quality", "predicted").agg(F.count(F.lit(1)).alias("n"))
