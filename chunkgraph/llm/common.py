"""Shared helpers of the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows are handed to Python in slices of at most this many text bytes, so one batch of very long documents stays small.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder below the shared checkpoint folder; in tests, where none is set, below the warehouse."""
    root = spark.conf.get("spark.checkpoint.dir", None) or f"{spark.conf.get('spark.sql.warehouse.dir')}/scratch"
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


#: Rows of a settled frame's partition, where the number of rows is known.
ROWS_A_PARTITION = 100_000


def settle(df: DataFrame, rows: int | None = None) -> DataFrame:
    """Write df to the shared folder and read it again: cuts lineage, and survives lost executors. rows: an upper bound of
    its rows, if known; small frames get few partitions then, large ones those that they have."""
    spark = df.sparkSession
    path = shared_dir(spark)
    if rows is not None:
        parts = rows // ROWS_A_PARTITION + 1
        df = df.coalesce(parts) if parts < int(spark.conf.get("spark.sql.shuffle.partitions")) else df
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Delete the files that `settle` wrote."""
    spark = df.sparkSession
    jvm = spark._jvm
    for name in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def crc_fold(doc_id: str, folds: int):
    """crc32 of the id as text, modulo the number of folds: decides which rows may teach a model."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % F.lit(folds)


#: Memos and tables that a worker process keeps between tasks: the operator's module, and how to empty them.
_KEPT: dict[str, Callable] = {}


def keep_between_tasks(owner: str, clear: Callable) -> None:
    _KEPT[owner] = clear


def give_back(owner: str | None) -> None:
    """A worker process serves the tasks of many operators in turn: what others than this one have kept goes."""
    others = [k for k in _KEPT if k != owner]
    for k in others:
        _KEPT.pop(k)()
    if others:
        gc.collect()
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):  # C libraries without it
            ctypes.CDLL(None).malloc_trim(0)


def text_slices(batches: Iterator[pa.RecordBatch], column: str = "text", owner: str | None = None) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that the text of each is about SLICE_BYTES, one row at least. owner: see `give_back`."""
    give_back(owner)
    for batch in batches:
        k = batch.schema.get_field_index(column)
        if k < 0 or batch.nbytes <= SLICE_BYTES:
            yield batch
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(k)), 0).to_pylist()
        start = size = 0
        for i, n in enumerate(lengths):
            if size and size + n > SLICE_BYTES:
                yield batch.slice(start, i - start)
                start, size = i, 0
            size += n
        if start < len(lengths):
            yield batch.slice(start)


def map_texts(df: DataFrame, make: Callable, schema: str) -> DataFrame:
    """mapInArrow over slices of bounded text size. make() runs once a task and returns slice -> RecordBatch."""

    def run(batches):
        work = make()
        for batch in text_slices(batches, owner=make.__module__):
            if batch.num_rows:
                yield work(batch)

    return df.mapInArrow(run, schema)


def map_groups(df: DataFrame, keys: list[str], work: Callable, schema: pa.Schema) -> DataFrame:
    """work(key, rows) -> tuples of the schema's longs, once for each key (a tuple); rows hold the other columns, as tuples.

    Groups are dealt by key and read in its order, a batch holds many; only one group's rows are held beyond its batch.
    """

    def run(batches):
        give_back(None)
        n, key, rows, out = len(keys), None, [], []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if row[:n] != key:
                    out += work(key, rows) if rows else []
                    key, rows = row[:n], []
                rows.append(row[n:])
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)
                out = []
        out += work(key, rows) if rows else []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    rest = [c for c in df.columns if c not in keys]
    dealt = df.select(*keys, *rest).repartition(*keys).sortWithinPartitions(*keys)
    return dealt.mapInArrow(run, ", ".join(f"{f.name} long" for f in schema))
