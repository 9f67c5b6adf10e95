"""spark.read.format("smallworld"): the small-world generator as a data source, dealt over partitions by vertex range."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Range(InputPartition):
    def __init__(self, lo: int, hi: int) -> None:
        self.lo, self.hi = lo, hi


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


class SmallWorldReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.n, self.d = int(options.get("n", 1000)), int(options.get("d", 4))
        self.beta, self.seed = float(options.get("beta", 0.3)), int(options.get("seed", 42))
        self.parts = int(options.get("partitions", 8))

    def partitions(self) -> list[Range]:
        step = max(1, -(-self.n // self.parts))
        return [Range(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)]

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        for lo in range(partition.lo, partition.hi, 50_000):
            v = np.repeat(np.arange(lo, min(partition.hi, lo + 50_000), dtype=np.uint64), self.d)
            i = np.tile(np.arange(1, self.d + 1, dtype=np.uint64), v.size // self.d)
            h = _mix((v * np.uint64(self.d + 1) + i) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(self.seed))
            go = (h >> np.uint64(32)).astype(np.float64) / 4294967296.0 < self.beta
            to = np.where(go, _mix(h + np.uint64(1)) % np.uint64(self.n), (v + i) % np.uint64(self.n))
            keep = to != v
            yield pa.RecordBatch.from_arrays([pa.array(v[keep].astype(np.int64)), pa.array(to[keep].astype(np.int64))], names=["src", "dst"])


class SmallWorldSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "smallworld"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> SmallWorldReader:
        return SmallWorldReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(SmallWorldSource)
