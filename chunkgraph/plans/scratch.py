"""Cutting lineage between the rounds of a loop, through the folder that all executors share."""

from __future__ import annotations

import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_lock, _writers = threading.Lock(), []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None) or f"{spark.conf.get('spark.sql.warehouse.dir')}/scratch"
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


@contextmanager
def _tidy(spark: SparkSession):
    """What is written meanwhile leaves no shuffle files behind; the setting goes back when the last writer is done."""
    with _lock:
        _writers.append(spark.conf.get(_CLEANUP, "false") if not _writers else _writers[0])
        spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        with _lock:
            before = _writers.pop()
            if not _writers:
                spark.conf.set(_CLEANUP, before)


def settle(df: DataFrame) -> DataFrame:
    """Write and read again: later reads do not run the plan, a lost executor costs no earlier round, and the shuffles of
    the plan are gone."""
    path = scratch_dir(df.sparkSession)
    with _tidy(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Delete what `settle` wrote, once no later plan reads it."""
    spark = df.sparkSession
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
