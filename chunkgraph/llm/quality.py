"""Quality score: random Fourier features of document statistics, ridge by normal equations summed over partitions,
isotonic calibration on labelled documents apart.

Every document's statistics come from its whole text; null and empty texts have the statistics of no characters. Rows
without a label, or in the held-out fold, teach nothing. With no labelled row, or one class only, the score is the
share of good labels (0.5 without labels). Several labels of a document each count; repeated documents are each scored.
Language, source and id of a document are never inputs.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import isotonic
from .common import crc_fold, map_texts, settle, table

FEATURES = 256
RIDGE = 1e-3
#: Width of the kernel: statistics are standardised, then divided by WIDTH.
WIDTH = 6.0
BINS = 1000
THRESHOLD = 0.7
#: One labelled document of so many, by a hash of the id, calibrates and is not learned from.
CALIBRATION = 5
#: What a code point below 256 counts as.
_CLASSES = ("letter", "digit", "space", "line", "stop", "pause", "bar", "mark", "quote", "other")
_CLASS_OF = np.full(256, 9, np.uint8)
for _k, _chars in enumerate(("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", "0123456789", " \t\r", "\n", ".!?", ",;:", "|", "#$%&*@^~_=+<>{}[]\\/", "\"'()-`")):
    _CLASS_OF[[ord(c) for c in _chars]] = _k
_CLASS_OF[128:] = 0  # bytes of longer code points, letters for the most part
_CAPITAL = np.zeros(256, bool)
_CAPITAL[65:91] = True
_SPLIT = re.compile(r"\s+")

STATISTICS = 26


def statistics(text: str | None) -> list[float]:
    text = text or ""
    raw = np.frombuffer(text.encode(), np.uint8)
    n = max(1, len(raw))
    seen = np.bincount(raw, minlength=256)
    share = np.bincount(_CLASS_OF, seen, len(_CLASSES)) / n
    words = text.split()
    w = max(1, len(words))
    distinct = len(set(words))
    lines = [x for x in text.split("\n") if x]
    rows = max(1, len(lines))
    lengths = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1, np.int64)
    letters = seen[_CLASS_OF == 0]
    p = letters[letters > 0] / max(1, letters.sum())
    pairs = len(set(zip(words, words[1:])))
    return [
        *share.tolist(),
        np.log1p(len(raw)), np.log1p(len(words)), float(lengths.mean()), float(lengths.std()), float(lengths.max() ** 0.5),
        distinct / w, np.log1p(distinct), pairs / w,
        len(set(lines)) / rows, np.log1p(len(lines)), np.log1p(len(raw) / rows),
        float(seen[_CAPITAL].sum()) / n, float(-(p * np.log(p)).sum()) if len(p) else 0.0,
        text.count(". ") / w, text.count(" | ") / w, float((lengths <= 3).mean()),
    ]


def document_statistics(df: DataFrame) -> DataFrame:
    """(doc_id, text) -> doc_id, stats."""

    def make():
        def work(batch):
            rows = np.array([statistics(t) for t in batch.column(1).to_pylist()], np.float32).reshape(-1, STATISTICS)
            flat = pa.ListArray.from_arrays(np.arange(len(rows) + 1, dtype=np.int32) * STATISTICS, pa.array(rows.ravel()))
            return pa.RecordBatch.from_arrays([batch.column(0), flat], ["doc_id", "stats"])

        return work

    return map_texts(df.select("doc_id", F.col("text").cast("string").alias("text")), make, "doc_id long, stats array<float>")


class FourierRidge:
    """cos(xW + b) features; fit from sums of partitions, so the whole labelled set counts and none of it is gathered."""

    def __init__(self, features: int = FEATURES, ridge: float = RIDGE, seed: int = 5):
        r = np.random.default_rng(seed)
        self.w, self.b = r.standard_normal((STATISTICS, features)) / WIDTH, r.uniform(0, 2 * np.pi, features)
        self.features, self.ridge = features, ridge
        self.mean, self.scale = np.zeros(STATISTICS), np.ones(STATISTICS)
        self.weights: np.ndarray | None = None
        self.share = 0.5
        self.knots = (np.array([0.0, 1.0]), np.array([0.0, 1.0]))

    def lift(self, stats: np.ndarray) -> np.ndarray:
        z = np.cos(np.clip((stats - self.mean) / self.scale, -8, 8) @ self.w + self.b) * (2 / self.features) ** 0.5
        return np.hstack([z, np.ones((len(z), 1))])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return np.full(len(stats), self.share) if self.weights is None else self.lift(stats) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(self.raw(stats), *self.knots), 0, 1)


def _summed(df: DataFrame, make, columns: int) -> np.ndarray:
    """Sum over all rows of make(stats, target) -> flat vector: one vector a partition, added up pairwise by groups."""

    def run(batches):
        total = None
        for batch in batches:
            if batch.num_rows:
                stats = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, STATISTICS).astype(float)
                part = make(stats, batch.column(1).to_numpy(zero_copy_only=False).astype(float))
                total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.astype("<f8").tobytes()], pa.binary())], ["sums"])

    def add(batches):
        total = None
        for batch in batches:
            for x in batch.column(0).to_pylist():
                part = np.frombuffer(x, "<f8")
                total = part.copy() if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["sums"])

    parts = df.mapInArrow(run, "sums binary")
    groups = parts.repartition(8).mapInArrow(add, "sums binary")
    out = np.zeros(columns)
    for row in groups.collect():  # at most eight vectors
        out += np.frombuffer(row["sums"], "<f8")
    return out


def fit(labelled: DataFrame, calibration: DataFrame | None = None, **options) -> FourierRidge:
    """labelled, calibration: stats, target (0 or 1). The calibration's rows are not learned from by the ridge; without any
    of both classes the scores are calibrated on the labelled ones."""
    model = FourierRidge(**options)
    d, k = STATISTICS, model.features + 1
    sums = _summed(labelled, lambda x, y: np.concatenate([[len(y), y.sum()], x.sum(0), (x**2).sum(0)]), 2 + 2 * d)
    n, good = sums[:2]
    if n:
        model.share = float(good / n)
    if not n or good in (0, n):
        return model
    model.mean = sums[2 : 2 + d] / n
    model.scale = np.sqrt(np.maximum(sums[2 + d :] / n - model.mean**2, 0)) + 1e-6

    def normal(x, y):
        z = model.lift(x)
        return np.concatenate([(z.T @ z).ravel(), z.T @ y])

    sums = _summed(labelled, normal, k * k + k)
    gram = sums[: k * k].reshape(k, k)
    model.weights = np.linalg.solve(gram + model.ridge * n * np.diag([*np.full(k - 1, 1.0 / k), 0.0]) + 1e-9 * np.eye(k), sums[k * k :])

    def binned(x, y):
        at = np.clip((model.raw(x) + 0.5) / 2 * BINS, 0, BINS - 1).astype(int)
        return np.concatenate([np.bincount(at, minlength=BINS), np.bincount(at, y, BINS)])

    sums = np.zeros(2 * BINS) if calibration is None else _summed(calibration, binned, 2 * BINS)
    if not 0 < sums[BINS:].sum() < sums[:BINS].sum():
        sums = _summed(labelled, binned, 2 * BINS)
    full = np.flatnonzero(sums[:BINS])
    model.knots = isotonic((full + 0.5) / BINS * 2 - 0.5, sums[BINS:][full] / sums[:BINS][full], sums[:BINS][full])
    return model


def score(stats: DataFrame, model: FourierRidge) -> DataFrame:
    """(doc_id, stats, ...) -> doc_id, score."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, STATISTICS).astype(float)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(x), pa.float64())], ["doc_id", "score"])

    return stats.select("doc_id", "stats").mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The result of op4: doc_id, held_out, score, predicted; learns where crc32(doc_id) mod 4 is not 2."""
    stats = settle(document_statistics(docs))
    marks = labels.select("doc_id", F.col("quality").alias("target")).where(F.col("target").isin(0, 1) & (crc_fold("doc_id", 4) != 2))
    known = settle(stats.join(marks, "doc_id").select("stats", "target", (F.pmod(F.xxhash64(F.col("doc_id"), F.lit(29)), F.lit(CALIBRATION)) == 0).alias("apart")))
    model = fit(known.where("NOT apart").select("stats", "target"), known.where("apart").select("stats", "target"))
    scored = score(stats, model)
    return scored.select("doc_id", F.coalesce(crc_fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def query(spark, sf_dir):
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
