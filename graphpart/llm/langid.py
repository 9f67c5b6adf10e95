"""Language ID: multinomial naive Bayes over hashed character n-grams; the matrix of log-probabilities is broadcast.

Log-probabilities are kept as integers (1/4096 of a nat), so sums are exact and equal texts get equal scores however
rows are batched. Every text is scored whole.

Edge cases: null texts and texts without a letter are ``und`` with score 0; a table without labelled rows gives ``und``
everywhere; ties go to the first language in alphabetical order; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from graphpart.llm.common import ID, TEXT, arrow_map, bounded_sample, give_back, remainder, strings

BITS = 15
UNIT = 4096.0
MAX_TRAIN_DOCS, MAX_TRAIN_CHARS = 4000, 30_000
SLICE_CHARS = 1 << 19


def _codes(text: str) -> np.ndarray:
    """The lower-cased text with a space before and after, as code points."""
    return np.frombuffer((" " + text.lower() + " ").encode("utf-32-le", "surrogatepass"), np.uint32)


def _slots(c: np.ndarray, n: int) -> np.ndarray:
    """Slots of the 2- and 3-grams that start at the first ``n`` code points."""
    two = c[:-1] * np.uint32(0x01000193) ^ c[1:] * np.uint32(0x9E3779B1)
    three = two[:-1] * np.uint32(0x85EBCA6B) ^ c[2:] * np.uint32(0xC2B2AE35)
    return np.concatenate([two[:n] * np.uint32(0x27D4EB2F) >> np.uint32(32 - BITS), three[:n] * np.uint32(0x165667B1) >> np.uint32(32 - BITS)])


def gram_slots(text: str) -> np.ndarray:
    """Slots of the 2- and 3-grams of the lower-cased text, with a space before and after."""
    c = _codes(text)
    return _slots(c, c.size)


def train(pairs: list[tuple[str, str]], alpha: float = 0.5) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Languages in alphabetical order, integer log-probabilities (slot, language), integer log-priors."""
    langs = sorted({y for _, y in pairs})
    counts = np.full((1 << BITS, len(langs)), alpha)
    docs = np.zeros(len(langs))
    for text, y in pairs:
        k = langs.index(y)
        counts[:, k] += np.bincount(gram_slots(text), minlength=1 << BITS)
        docs[k] += 1
    table = np.round(UNIT * (np.log(counts) - np.log(counts.sum(axis=0)))).astype(np.int32)
    return langs, table, np.round(UNIT * np.log((docs + 1) / (docs + 1).sum())).astype(np.int64) if langs else np.zeros(0, np.int64)


def fit_langid(docs: DataFrame, train_only: bool = True, max_docs: int = MAX_TRAIN_DOCS, max_chars: int = MAX_TRAIN_CHARS) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Train on a bounded sample of rows with a language; with ``train_only``, held-out rows (crc32 of the id, mod 4, is 2) are never seen."""
    rows = docs.select(ID, "lang")
    model = train(bounded_sample(docs, rows.where(remainder(ID, 4) != 2) if train_only else rows, "lang", max_docs, max_chars))
    give_back()
    return model


def predict(texts: list[str], langs: list[str], table: np.ndarray, prior: np.ndarray) -> tuple[list[str], list[float]]:
    pred, score = [], []
    for text in texts:
        if not langs or not any(map(str.isalpha, text)):
            pred.append("und")
            score.append(0.0)
            continue
        total = prior.copy()
        codes = _codes(text)
        for i in range(0, codes.size, SLICE_CHARS):  # a slice sees the two code points after it: every gram counts once
            if codes.size - i > 1:
                total = total + table[_slots(codes[i : i + SLICE_CHARS + 2], SLICE_CHARS)].sum(axis=0, dtype=np.int64)
        k = int(total.argmax())
        pred.append(langs[k])
        score.append(float(1 / np.exp(np.clip((total - total[k]) / UNIT, -700, 0)).sum()))
    return pred, score


def identify_languages(docs: DataFrame, model: tuple[list[str], np.ndarray, np.ndarray]) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pred, score = predict(strings(batch, TEXT), *shared.value)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=[ID, "held_out", "lang_pred", "score"])

    rows = docs.select(ID, (remainder(ID, 4) == 2).alias("held_out"), TEXT)
    return arrow_map(rows, run, f"{ID} {docs.schema[ID].dataType.simpleString()}, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, model: tuple[list[str], np.ndarray, np.ndarray], least: float = 0.5) -> DataFrame:
    """The rows of ``docs``, all columns, whose language is known with a posterior of at least ``least``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pred, score = predict(strings(batch, TEXT), *shared.value)
            yield batch.filter(pa.array([p != "und" and s >= least for p, s in zip(pred, score, strict=True)], pa.bool_()))

    return arrow_map(docs, run, docs.schema)
