"""Helpers shared by the training-data operators: code shipping, input columns, bounded samples, checkpoints."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from graphpart.session import durable, ship  # noqa: F401  the operators' lineage cut

TEXT, ID = "text", "doc_id"
BATCH_ROWS = 1000


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def give_back() -> None:
    """Freed memory of this process goes back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # no glibc
        pass


def _tidy(fn: Callable) -> Callable:
    """fn, and after a task's last batch its freed memory goes back (workers live on for later stages)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fn(batches)
        give_back()

    return run


def arrow_map(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | StructType) -> DataFrame:
    """mapInArrow with the package shipped first, over batches of at most BATCH_ROWS rows (texts can be long)."""
    ship(df.sparkSession)
    if int(df.sparkSession.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) not in range(1, BATCH_ROWS + 1):
        df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return df.mapInArrow(_tidy(fn), schema)


def strings(batch: pa.RecordBatch, name: str) -> list[str]:
    """A text column as Python strings, null as empty."""
    return [x or "" for x in batch.column(name).to_pylist()]


def remainder(id_col: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo; null ids count as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def bounded_sample(docs: DataFrame, labelled: DataFrame, label: str, max_docs: int, max_chars: int) -> list[tuple[str, object]]:
    """At most ``max_docs`` (text, label) pairs of at most ``max_chars`` characters each, smallest hashes of the id first.

    ``labelled`` holds (doc_id, label). The ids come from a bounded top-k; only their texts are read, one per id.
    The driver never holds more than max_docs * max_chars characters.
    """
    picked = labelled.where(F.col(ID).isNotNull() & F.col(label).isNotNull()).select(ID, F.col(label).alias("_label")).orderBy(F.xxhash64(ID), ID, "_label").limit(max_docs)
    rows = (
        docs.select(ID, TEXT)
        .where(F.col(TEXT).isNotNull() & (F.length(TEXT) <= max_chars))
        .join(F.broadcast(picked), ID)  # at most max_docs rows of an id and a label
        .groupBy(ID)
        .agg(F.min(TEXT).alias(TEXT), F.min("_label").alias("_label"))
        .collect()
    )
    return [(r[TEXT], r["_label"]) for r in sorted(rows, key=lambda r: r[ID])]
