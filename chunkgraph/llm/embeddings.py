"""Embedding near-duplicates by an epsilon grid order join.

Unit vectors are projected on their leading principal directions (from a covariance summed over partitions), sorted by
label and by the grid cells of width epsilon in these directions, and cut into sequence intervals (blocks). Blocks whose
bounding boxes are closer than epsilon meet in one task, which joins them recursively: two intervals farther apart than
epsilon are skipped, large ones are halved, small ones are compared by a matrix product in double precision. Equal
vectors of a label are one point with a count, so copies are never expanded; a task returns counts and a spanning set of
links, not pairs.

Vectors are doubles throughout, and labels of any type are compared as text. Vectors that are null, of norm zero, or hold a null or a non-finite component, and rows with a null label or id, link
with nothing (their component is their own id). Rows of one id with equal label and vector are one vector. Vectors of
different lengths are at no distance and never link.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle, table
from .components import components

THRESHOLD = 0.98
DIRECTIONS = 8
#: Vectors of a block, and of the intervals that are compared by a matrix product.
BLOCK, LEAF = 1024, 128
#: Directions in whose cells blocks meet.
MEETING = 3
_BLOCK_TYPE = "block long, label string, width int, low array<double>, high array<double>, ids binary, counts binary, vectors binary"


def usable(vector: Column) -> Column:
    """Neither null nor zero, all components finite."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(F.size(vector) > 0, F.lit(False)) & ~F.coalesce(bad, F.lit(True)) & F.exists(vector, lambda x: x != 0)


def _matrix(column, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, width)


def _units(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(1, keepdims=True)  # so that squares neither vanish nor overflow
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def directions(points: DataFrame, width: int, count: int = DIRECTIONS) -> np.ndarray:
    """Leading eigenvectors (as columns) of the covariance of unit vectors, from sums of partitions."""

    def sums(batches):
        total = np.zeros(1 + width + width * width)
        for batch in batches:
            if batch.num_rows:
                u = _units(_matrix(batch.column(0), width))
                total += np.concatenate(([len(u)], u.sum(0), (u.T @ u).ravel()))
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

    def add(batches):
        total = np.zeros(1 + width + width * width)
        for batch in batches:
            for x in batch.column(0).to_pylist():
                total += np.frombuffer(x)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

    parts = points.select("vector").mapInArrow(sums, "sums binary").repartition(8).mapInArrow(add, "sums binary").collect()  # eight rows
    total = np.sum([np.frombuffer(r["sums"]) for r in parts], axis=0)
    n, mean = max(total[0], 1), total[1 : 1 + width] / max(total[0], 1)
    values, vectors = np.linalg.eigh(total[1 + width :].reshape(width, width) / n - np.outer(mean, mean))
    return vectors[:, np.argsort(-values, kind="stable")[:count]]


def _apart(low_a, high_a, low_b, high_b) -> float:
    """Distance of two boxes: no two of their points are closer."""
    gap = np.maximum(0, np.maximum(low_a - high_b, low_b - high_a))
    return float(np.sqrt((gap * gap).sum()))


def join_intervals(a, b, threshold: float, epsilon: float, found: list) -> None:
    """a, b: (first, end, unit vectors, projections). Appends (rows of a, rows of b) with cosine at or over threshold."""
    if _apart(a[3][a[0] : a[1]].min(0), a[3][a[0] : a[1]].max(0), b[3][b[0] : b[1]].min(0), b[3][b[0] : b[1]].max(0)) > epsilon:
        return
    if a[1] - a[0] <= LEAF and b[1] - b[0] <= LEAF:
        i, j = np.nonzero(a[2][a[0] : a[1]] @ b[2][b[0] : b[1]].T >= threshold)
        if len(i):
            found.append((i + a[0], j + b[0]))
        return
    large, small, swap = (a, b, False) if a[1] - a[0] >= b[1] - b[0] else (b, a, True)
    middle = (large[0] + large[1]) // 2
    for first, end in ((large[0], middle), (middle, large[1])):
        half = (first, end, *large[2:])
        join_intervals(*((small, half) if swap else (half, small)), threshold, epsilon, found)


def _spanning(n: int, i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
    """A spanning set of the links among n points: each point with the least of its component."""
    label = np.arange(n)
    while True:
        least = label.copy()
        np.minimum.at(least, i, label[j])
        np.minimum.at(least, j, label[i])
        least = least[least]
        if (least == label).all():
            return [(int(least[k]), k) for k in np.flatnonzero(least != np.arange(n))]
        label = least


def blocks(points: DataFrame, width: int, epsilon: float, axes: np.ndarray) -> DataFrame:
    """Sequence intervals of the epsilon grid order: see _BLOCK_TYPE. points: rep, label, vector, copies."""
    names = [f"c{k}" for k in range(axes.shape[1])]

    def cells(batches):
        for batch in batches:
            if batch.num_rows:
                at = np.floor(_units(_matrix(batch.column("vector"), width)) @ axes / epsilon).astype(np.int32)
                yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(c) for c in at.T)], [*batch.schema.names, *names])

    kinds = "rep long, label string, vector array<double>, copies long, " + ", ".join(f"{n} int" for n in names)
    sorted_rows = points.select("rep", "label", "vector", "copies").mapInArrow(cells, kinds)
    order = ["label", *names, "rep"]
    parts = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    sorted_rows = sorted_rows.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())

    def cut(batches):
        number, held = 0, []

        def emit(rows):
            nonlocal number
            x = _units(_matrix(rows.column("vector").combine_chunks(), width))
            p = x @ axes
            block = (rows.column("part")[0].as_py() << 32) + number
            number += 1
            return [block, rows.column("label")[0].as_py(), width, p.min(0).tolist(), p.max(0).tolist(), rows.column("rep").to_numpy().astype("<i8").tobytes(), rows.column("copies").to_numpy().astype("<i8").tobytes(), x.tobytes()]

        def pack(out):
            kinds = [pa.int64(), pa.string(), pa.int32(), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.binary(), pa.binary(), pa.binary()]
            names = [c.split()[0] for c in _BLOCK_TYPE.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names)

        def ready(rows, last):
            """Whole blocks of the rows held; what may still grow stays."""
            start, n = 0, rows.num_rows
            label = np.array(rows.column("label").to_pylist(), object)
            change = np.flatnonzero(label[1:] != label[:-1]) + 1
            for end in [*change.tolist(), n]:
                while end - start > BLOCK or (end - start and (end < n or last)):
                    stop = min(end, start + BLOCK)
                    yield pack([emit(rows.slice(start, stop - start))])
                    start = stop
            held.clear()
            if start < n:
                held.append(rows.slice(start))

        for batch in batches:
            held.append(pa.Table.from_batches([batch]))
            if sum(h.num_rows for h in held) > 4 * BLOCK:
                yield from ready(pa.concat_tables(held), False)
        if held and sum(h.num_rows for h in held):
            yield from ready(pa.concat_tables(held), True)

    return sorted_rows.mapInArrow(cut, _BLOCK_TYPE)


def block_pairs(made: DataFrame, epsilon: float) -> DataFrame:
    """(a, b): blocks of a label whose boxes are at most epsilon apart, each pair once, a block with itself included.

    Boxes meet by the cells that they overlap in the first MEETING directions, so no block is compared with all others;
    of the cells that two boxes share the one with the greater of both lowest cells gives the pair.
    """
    cell = lambda x: F.coalesce(F.floor(x / epsilon).cast("int"), F.lit(0))  # noqa: E731  (vectors of fewer components)
    reach = made.select("block", "label", "width", "low", "high")
    axes = range(min(MEETING, DIRECTIONS))
    for k in axes:
        reach = reach.withColumn(f"cell{k}", F.explode(F.sequence(cell(F.get("low", k)), cell(F.get("high", k)) + 1)))
    keys = ["label", "width", *(f"cell{k}" for k in axes)]
    left = reach.select(F.col("block").alias("a"), *keys, F.col("low").alias("low_a"), F.col("high").alias("high_a"))
    right = reach.select(F.col("block").alias("b"), *keys, F.col("low").alias("low_b"), F.col("high").alias("high_b"))
    gap = F.zip_with(F.arrays_zip("low_a", "high_a"), F.arrays_zip("low_b", "high_b"), lambda x, y: F.greatest(F.lit(0.0), x["low_a"] - y["high_b"], y["low_b"] - x["high_a"]))
    near = F.aggregate(gap, F.lit(0.0), lambda s, g: s + g * g) <= epsilon * epsilon
    for k in axes:
        near = (F.col(f"cell{k}") == cell(F.greatest(F.get("low_a", k), F.get("low_b", k)))) & near
    return left.join(right, keys).where((F.col("a") <= F.col("b")) & near).select("a", "b")


def linked(points: DataFrame, width: int, threshold: float = THRESHOLD) -> DataFrame:
    """a, b, n: for b null, n more links of point a; else a link of a spanning set."""
    epsilon = float(np.sqrt(max(0.0, 2 - 2 * threshold))) + 1e-9
    axes = directions(points, width)
    made = settle(blocks(points, width, epsilon, axes))
    data = made.select("block", "ids", "counts", "vectors", "low")
    pairs = block_pairs(made, epsilon)
    side = lambda n: data.select(*(F.col(c).alias(f"{c}_{n}") for c in ("ids", "counts", "vectors")), F.col("block").alias(n))
    met = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "ids_a", "counts_a", "vectors_a", "ids_b", "counts_b", "vectors_b")

    def compare(batches):
        for batch in batches:
            for a, b, ids_a, counts_a, vectors_a, ids_b, counts_b, vectors_b in zip(*(c.to_pylist() for c in batch.columns)):
                read = lambda ids, counts, v: (np.frombuffer(ids, "<i8"), np.frombuffer(counts, "<i8"), np.frombuffer(v).reshape(-1, width))
                (ia, ca, xa), (ib, cb, xb) = read(ids_a, counts_a, vectors_a), read(ids_b, counts_b, vectors_b)
                found: list = []
                join_intervals((0, len(xa), xa, xa @ axes), (0, len(xb), xb, xb @ axes), threshold, epsilon, found)
                if not found:
                    continue
                i, j = (np.concatenate([f[k] for f in found]) for k in (0, 1))
                if a == b:
                    i, j = i[i != j], j[i != j]
                    ids = ia
                    more = np.bincount(i, cb[j], len(ia))
                else:
                    ids = np.concatenate((ia, ib))
                    more = np.concatenate((np.bincount(i, cb[j], len(ia)), np.bincount(j, ca[i], len(ib))))
                    j = j + len(ia)
                if not len(i):
                    continue
                some = np.flatnonzero(more)
                tree = _spanning(len(ids), i, j)
                first = np.concatenate((ids[some], ids[[t[0] for t in tree]]))
                second = [None] * len(some) + ids[[t[1] for t in tree]].tolist()
                yield pa.RecordBatch.from_arrays([pa.array(first), pa.array(second, pa.int64()), pa.array(np.concatenate((more[some], np.zeros(len(tree)))).astype(np.int64))], ["a", "b", "n"])

    return met.mapInArrow(compare, "a long, b long, n long")


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(vec_id, embedding, label) -> vec_id, n_links, component_id, kept; one row for each row of vectors."""
    rows = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("vector"), F.col("label").cast("string").alias("label"))
    ok = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & usable(F.col("vector"))
    good, rest = rows.where(ok), rows.where(~ok)
    points = settle(good.groupBy("label", "vector").agg(F.min("vec_id").alias("rep"), F.count_distinct("vec_id").alias("copies")))
    widths = [r[0] for r in points.select(F.size("vector")).distinct().collect()]  # one, as a rule
    found = None
    for width in widths:
        part = linked(points.where(F.size("vector") == width), width, threshold)
        found = part if found is None else found.unionAll(part)
    plain = rest.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    if found is None:
        return plain
    found = settle(found)
    counts = found.where(F.col("b").isNull()).groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("more"))
    groups = components(found.where(F.col("b").isNotNull()).select("a", "b")).withColumnRenamed("node", "rep")
    judged = points.join(counts, "rep", "left").join(groups, "rep", "left")
    judged = judged.select("label", "vector", (F.coalesce("more", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    return good.join(judged, ["label", "vector"]).select("vec_id", F.col("n_links").cast("long").alias("n_links"), "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept")).unionAll(plain)


def query(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "embeddings"))


ORACLE_SQL = """
WITH RECURSIVE good AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
link AS (SELECT x.vec_id AS a, y.vec_id AS b FROM good x JOIN good y ON x.label = y.label AND x.vec_id <> y.vec_id AND len(x.v) = len(y.v)
         WHERE list_cosine_similarity(x.v, y.v) >= 0.98),
reach(a, b) AS (SELECT vec_id, vec_id FROM good UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a),
least AS (SELECT a AS vec_id, min(b) AS c FROM reach GROUP BY a),
deg AS (SELECT a AS vec_id, count(*) AS n FROM link GROUP BY a)
SELECT e.vec_id, CAST(coalesce(deg.n, 0) AS BIGINT) AS n_links, CAST(coalesce(least.c, e.vec_id) AS BIGINT) AS component_id,
       e.vec_id = coalesce(least.c, e.vec_id) AS kept
FROM embeddings e LEFT JOIN deg ON e.vec_id = deg.vec_id LEFT JOIN least ON e.vec_id = least.vec_id
"""
