"""Cost measures: bytes of a graph by format, sizes of chunks against their bounds, work of traversals, ratios."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.codec import byte_length
from ..operators import sets

#: Bytes of a vertex in a flat snapshot, of a vertex and an edge in plain trees, of a vertex and a head in
#: chunked trees, and of an uncoded element.
FLAT_VERTEX, PLAIN_VERTEX, PLAIN_EDGE, CHUNK_VERTEX, CHUNK_HEAD, RAW_ELEMENT = 16, 48, 32, 56, 48, 4
#: The published graphs, (label, vertices, directed edges).
PUBLISHED_GRAPHS = (
    ("G1", 4847571, 85702474), ("G2", 3072627, 234370166), ("G3", 41652231, 2405026092),
    ("G4", 978408098, 74744358622), ("G5", 1724573718, 124141874032), ("G6", 3563602789, 225840663232),
)


def published_memory(spark: SparkSession) -> DataFrame:
    """(graph, flat_gib, plain_gib) of the published graphs by the byte model."""
    return modelled_memory(spark.createDataFrame(list(PUBLISHED_GRAPHS), "graph string, n long, m long"))


def modelled_memory(rows: DataFrame) -> DataFrame:
    """(graph, flat_gib, plain_gib) of graphs (graph, n, m) by the byte model."""
    gib = float(1 << 30)
    return rows.select("graph", F.round(F.col("n") * FLAT_VERTEX / gib, 6).alias("flat_gib"), F.round((F.col("n") * PLAIN_VERTEX + F.col("m") * PLAIN_EDGE) / gib, 6).alias("plain_gib"))


def tail_deltas(chunks: DataFrame) -> DataFrame:
    """(owner, head, delta): first tail element of each chunk as it is, then the differences."""
    before = F.lag("elem").over(Window.partitionBy("owner", "head").orderBy("elem"))
    tails = chunks.select("owner", "head", F.explode("elems").alias("elem"))
    return tails.select("owner", "head", (F.col("elem") - F.coalesce(before, F.lit(0))).alias("delta"))


def memory_formats(chunks: DataFrame) -> DataFrame:
    """One row: n, m, heads, payload bytes, and the bytes of each format; saving of the coded one over plain trees."""
    shape = chunks.agg(F.count_distinct("owner").alias("n"), F.sum(sets.weight()).cast("long").alias("m"), F.count("head").alias("heads"))
    coded = tail_deltas(chunks).agg(F.sum(byte_length(F.col("delta"))).cast("long").alias("payload"))
    both = shape.join(coded, how="cross")  # one row each
    base = F.col("n") * CHUNK_VERTEX + F.col("heads") * CHUNK_HEAD
    out = both.select("*", (F.col("n") * FLAT_VERTEX).alias("flat_bytes"), (F.col("n") * PLAIN_VERTEX + F.col("m") * PLAIN_EDGE).alias("plain_bytes"), (base + (F.col("m") - F.col("heads")) * RAW_ELEMENT).alias("chunked_bytes"), (base + F.col("payload")).alias("coded_bytes"))
    return out.withColumn("saving", F.round(F.col("plain_bytes") / F.col("coded_bytes"), 6))


def ratios(ours: dict[str, float], theirs: dict[str, float]) -> dict[str, float]:
    """Other system's figure over ours, for each key that both have; and their mean."""
    out = {k: theirs[k] / ours[k] for k in sorted(ours.keys() & theirs.keys()) if ours[k]}
    return out | {"average": sum(out.values()) / len(out)} if out else out
