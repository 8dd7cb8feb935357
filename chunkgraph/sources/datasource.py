"""The update generator as a Python data source, for batch reads and as an endless stream; both draw whole Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from ..functions.hashing import MODULUS, portable_hash_array

#: Rows of one partition of a batch read, of one Arrow batch, and of one fetch of a stream.
PARTITION_ROWS, BATCH_ROWS, FETCH_ROWS = 1 << 22, 1 << 16, 2000


def draws(first: int, end: int, scale: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Draws first to end - 1 as (i, src, dst); the same as `rmat` gives."""
    return draws_of(np.arange(first, end, dtype=np.int64), scale, seed)


def draws_of(ids, scale: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of given numbers, not negative."""
    i = np.asarray(ids, np.int64)
    src, dst = np.zeros(len(i), np.int64), np.zeros(len(i), np.int64)
    for level in range(scale):
        u = portable_hash_array(i, seed + level) * 10
        src = src * 2 + (u >= 6 * MODULUS)
        dst = dst * 2 + ((u >= 5 * MODULUS) & (u < 6 * MODULUS) | (u >= 7 * MODULUS))
    return i, src, dst


class _Range(InputPartition):
    def __init__(self, first: int, end: int):
        self.first, self.end = first, end


class _Reader(DataSourceReader):
    def __init__(self, scale: int, count: int, seed: int):
        self.scale, self.count, self.seed = scale, count, seed

    def partitions(self):
        return [_Range(k, min(self.count, k + PARTITION_ROWS)) for k in range(0, self.count, PARTITION_ROWS)]

    def read(self, partition):
        for k in range(partition.first, partition.end, BATCH_ROWS):
            columns = draws(k, min(partition.end, k + BATCH_ROWS), self.scale, self.seed)
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["i", "src", "dst"])


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, scale: int, seed: int):
        self.scale, self.seed = scale, seed

    def initialOffset(self):
        return {"at": 0}

    def _rows(self, first, end):
        return zip(*(c.tolist() for c in draws(first, end, self.scale, self.seed)))

    def read(self, start):
        end = start["at"] + FETCH_ROWS
        return self._rows(start["at"], end), {"at": end}

    def readBetweenOffsets(self, start, end):
        return self._rows(start["at"], end["at"])

    def commit(self, end):
        pass


class RmatSource(DataSource):
    """format("rmat"), options scale, count (batch) and seed; columns i, src, dst."""

    @classmethod
    def name(cls):
        return "rmat"

    def schema(self):
        return "i bigint, src bigint, dst bigint"

    def _options(self):
        return int(self.options.get("scale", 10)), int(self.options.get("count", 1000)), int(self.options.get("seed", 1))

    def reader(self, schema):
        return _Reader(*self._options())

    def simpleStreamReader(self, schema):
        scale, _, seed = self._options()
        return _Stream(scale, seed)
