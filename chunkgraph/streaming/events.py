"""Update streams with Structured Streaming: windows, late rows, stateful degrees, and batches applied to a version store."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..operators.graph import Graph
from ..plans.scratch import scratch_dir, table
from ..sources.store import VersionStore


def stream_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """`events` as a file stream; ts becomes a TIMESTAMP (in the session's zone), which watermarks need."""
    schema = table(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(rows: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Runs a stream over what is there now, and returns what it has written as Parquet, one folder a micro-batch, so that
    a batch that is replayed replaces itself. append: all batches; complete: the last one; update: of each key the last."""
    spark, path = rows.sparkSession, scratch_dir(rows.sparkSession)

    def write(batch, number):
        batch.write.mode("overwrite").parquet(f"{path}/batch={number:09d}")

    query = rows.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", scratch_dir(spark)).trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.schema(rows.schema.add("batch", "string")).parquet(path)
    if mode == "complete":
        out = out.where(F.col("batch") == out.agg(F.max("batch")).first()[0])
    elif mode == "update":
        rest = [c for c in rows.columns if c not in keys]
        out = out.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("_last")).select(*keys, "_last.*")
    return out.select(*rows.columns)


def _counted(rows: DataFrame, width: str, slide: str | None) -> DataFrame:
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.withWatermark("ts", "1 day").groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))


def run_windows(spark: SparkSession, sf_dir: str, width: str, slide: str | None) -> DataFrame:
    """(start_us, event_type, n): tumbling or sliding windows with a day of lateness, open ones included."""
    return run_to_end(_counted(stream_events(spark, sf_dir), width, slide), "update", ["w", "event_type"]).select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


def run_sessions(spark: SparkSession, sf_dir: str, gap: str) -> DataFrame:
    """(user_id, start_us, n): sessions that end after a gap."""
    counted = stream_events(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_end(counted, "complete").select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def run_late(spark: SparkSession, sf_dir: str, held: int = 50) -> DataFrame:
    """One row: events counted, events that came too late for their day's window. Every `held`-th event arrives in a third
    file. Rows are late by the watermark of the batch before theirs, which the first file has set to a day before its newest."""
    events, folder = table(spark, sf_dir, "events"), scratch_dir(spark)
    at = F.col("event_id") % held
    for k, part in enumerate((events.where(at > 1), events.where(at == 1), events.where(at == 0))):
        part.coalesce(1).write.parquet(f"{folder}/part{k}")
    rows = spark.readStream.schema(events.schema).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", 1).parquet(folder)
    counted = run_to_end(_counted(rows.withColumn("ts", F.col("ts").cast("timestamp")), "1 day", None), "update", ["w", "event_type"])
    total = events.agg(F.count("*").alias("total"))
    return counted.agg(F.sum("n").alias("counted")).join(total, how="cross").select("counted", (F.col("total") - F.col("counted")).alias("late"))  # one row each


def run_deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, n) of a stream in which every row comes twice, the second an hour later; repeats within the watermark go."""
    rows = stream_events(spark, sf_dir)
    twice = rows.withColumn("k", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("ts", F.col("ts") + F.expr("make_dt_interval(0, k)")).withWatermark("ts", "2 hours")
    once = twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")
    return run_to_end(once, "append").groupBy("event_type").agg(F.count("*").alias("n"))


def run_stateful_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, deg): distinct targets of each user. The state is one count for each (user, target), so no state grows with a
    user's degree; a pair is passed on when it is new."""
    rows = stream_events(spark, sf_dir).select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k IS NOT NULL")

    def update(key, parts, state):
        known = state.get[0] if state.exists else 0
        state.update((known + sum(map(len, parts)),))
        if not known:
            yield pd.DataFrame({"vid": [key[0]], "k": [key[1]]})

    new = rows.groupBy("user_id", "k").applyInPandasWithState(update, "vid long, k long", "events long", "append", GroupStateTimeout.NoTimeout)
    return run_to_end(new, "append").groupBy("vid").agg(F.count("*").alias("deg"))


def event_updates(events: DataFrame) -> DataFrame:
    """(seq, op, src, dst): an error deletes the edge (user, k), anything else inserts it."""
    return events.select(F.col("event_id").alias("seq"), F.when(F.col("event_type") == "error", "D").otherwise("I").alias("op"), (F.col("user_id") * 2).alias("src"), (F.get_json_object("props", "$.k").cast("long") * 2 + 1).alias("dst"))


def apply_updates(updates: DataFrame, store: VersionStore, checkpoint: str):
    """A running query that applies each micro-batch as one version; a batch that is replayed changes nothing."""
    return updates.writeStream.foreachBatch(lambda batch, number: store.apply(batch, batch_id=number)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def apply_event_stream(spark: SparkSession, sf_dir: str) -> Graph:
    store = VersionStore(spark, scratch_dir(spark), b=8)
    store.publish(Graph.from_edges(spark.createDataFrame([], "src long, dst long"), b=8))
    apply_updates(event_updates(stream_events(spark, sf_dir)), store, scratch_dir(spark)).awaitTermination()
    return store.graph()
