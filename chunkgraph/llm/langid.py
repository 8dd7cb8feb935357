"""Language of a document by a string kernel: presence of n-grams of several lengths (blended spectrum), Nystroem
landmarks, one-versus-rest kernel ridge regression, scored by products of batches of documents with the landmarks.

Two documents are as alike as their sets of letter n-grams (lengths 1 to 4, words padded with a space): the size of the
intersection over the geometric mean of the sizes. n-grams are hashed into 2^18 slots, and all slots that any landmark
holds count. A document's presence row is sparse, so its product with the landmarks adds up the landmarks' rows of its
own slots; in scoring these rows are multiplied by the dual weights beforehand, which gives the same numbers. Training
takes a bounded sample (about TRAIN_PER_LANGUAGE documents a language, chosen by a hash of the id), of which the driver
gets sets of slots, never texts; whole texts are read for training and scoring. Null texts and texts without a letter get `und` with score 1; where nothing can be learned, all others get `und`
with score 0. Source, lang and id of a document are never inputs of its prediction; repeated documents are each judged.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_fold, map_texts, table, text_slices

SLOTS = 1 << 18
LENGTHS = (1, 2, 3, 4)
#: Documented bounds of the training sample, and of the landmarks.
TRAIN_PER_LANGUAGE = 400
LANDMARKS = 160
RIDGE = 1e-3
SHARPNESS = 6.0
UNDETERMINED = "und"
_NOT_LETTERS = re.compile(r"[\W\d_]+")
_LETTER = re.compile(r"[^\W\d_]")
BLOCK = 64


def has_letter(text: str | None) -> bool:
    return bool(text) and any(m.group().isalpha() for m in _LETTER.finditer(text))


def slots(text: str) -> np.ndarray:
    """Hashed n-grams of the whole text, with repeats."""
    plain = f" {_NOT_LETTERS.sub(' ', text.lower())} "
    codes = np.frombuffer(plain.encode("utf-32-le"), np.uint32)
    out, rolling = [], np.zeros(len(codes), np.uint32)
    for n in range(1, max(LENGTHS) + 1):
        rolling = (rolling[: len(codes) - n + 1] * np.uint32(0x01000193)) ^ codes[n - 1 :]
        mixed = rolling * np.uint32(0x9E3779B1)
        mixed ^= mixed >> np.uint32(15)
        if n in LENGTHS:
            out.append((mixed * np.uint32(0x85EBCA77) + np.uint32(n)) >> np.uint32(14))
    return np.concatenate(out)


def presence(text: str, flags: np.ndarray) -> np.ndarray:
    """The distinct slots of a text, ascending. flags: a buffer of SLOTS false values, which it is again afterwards."""
    found = slots(text)
    flags[found] = True
    out = np.flatnonzero(flags)
    flags[found] = False
    return out.astype(np.int32)


def gathered(rows: list[np.ndarray], place: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Product of sparse presence rows with a table that has a row for each known slot (place: its number, or -1)."""
    spots = [(p := place[r])[p >= 0] for r in rows]
    out = np.zeros((len(rows), table.shape[1]))
    some = [k for k, s in enumerate(spots) if len(s)]
    if some:
        sizes = np.array([len(spots[k]) for k in some])
        out[some] = np.add.reduceat(table[np.concatenate([spots[k] for k in some])], np.cumsum(sizes) - sizes, axis=0)
    return out


class KernelRidge:
    """languages; place (slot -> row, or -1); weights (a row for each known slot: landmarks times dual weights)."""

    def __init__(self, languages: list[str], place: np.ndarray, weights: np.ndarray):
        self.languages, self.place, self.weights = languages, place, weights

    def scores(self, rows: list[np.ndarray]) -> np.ndarray:
        return gathered(rows, self.place, self.weights) / np.sqrt(np.maximum([len(r) for r in rows], 1))[:, None]

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        flags, names, sure = np.zeros(SLOTS, bool), [], []
        for start in range(0, len(texts), BLOCK):
            rows = [presence(t, flags) for t in texts[start : start + BLOCK]]
            z = self.scores(rows) * SHARPNESS
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            best = p.argmax(1)
            names += [self.languages[b] for b in best]
            sure += p[np.arange(len(rows)), best].tolist()
        return names, sure


def fit(rows: list[np.ndarray], languages: list[str]) -> KernelRidge | None:
    """Nystroem map from evenly dealt landmarks, then ridge regression of each language against the rest. rows: sets of slots."""
    names = sorted(set(languages))
    if not names:
        return None
    by_name = {name: [k for k, y in enumerate(languages) if y == name] for name in names}
    share = max(1, LANDMARKS // len(names))
    marks = [rows[k] for name in names for k in by_name[name][:share]]
    known = np.unique(np.concatenate(marks))
    place = np.full(SLOTS, -1, np.int32)
    place[known] = np.arange(len(known))
    landmarks = np.zeros((len(known), len(marks)), np.float32)
    for k, r in enumerate(marks):
        landmarks[place[r], k] = 1 / np.sqrt(len(r))
    kernel = lambda some: gathered(some, place, landmarks) / np.sqrt([max(1, len(r)) for r in some])[:, None]
    values, vectors = np.linalg.eigh(kernel(marks))
    good = values > values.max() * 1e-6
    root = vectors[:, good] / np.sqrt(values[good])
    lifted = np.concatenate([kernel(rows[k : k + BLOCK]) for k in range(0, len(rows), BLOCK)]) @ root
    target = np.array([[1.0 if y == name else -1.0 for name in names] for y in languages])
    weight = 1.0 / np.array([len(by_name[y]) for y in languages])[:, None]
    gram = lifted.T @ (lifted * weight) + RIDGE * np.eye(lifted.shape[1])
    beta = np.linalg.solve(gram, lifted.T @ (target * weight))
    return KernelRidge(names, place, landmarks @ (root @ beta).astype(np.float32))


def training_rows(docs: DataFrame, learn=None) -> tuple[list[np.ndarray], list[str]]:
    """(sets of slots, languages) of a bounded sample: of each language, documents whose hashed id is below a share that
    gives about the bound."""
    usable = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.col("text") != ""))
    usable = usable if learn is None else usable.where(learn)
    counts = {r["lang"]: r["count"] for r in usable.groupBy("lang").count().collect()}
    if not counts:
        return [], []
    spot = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit(17)), F.lit(1 << 20)) / float(1 << 20)
    share = F.lit(0.0)
    for name, n in counts.items():
        share = F.when(F.col("lang") == name, min(1.0, TRAIN_PER_LANGUAGE / n)).otherwise(share)

    def sets(batches):
        flags = np.zeros(SLOTS, bool)
        for batch in text_slices(batches):
            texts = batch.column(2).to_pylist()
            some = [presence(t, flags).tobytes() if has_letter(t) else None for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(some, pa.binary())], ["doc_id", "lang", "slots"])

    sample = usable.where(spot < share).select("doc_id", "lang", F.col("text").cast("string").alias("text"))
    rows = sample.mapInArrow(sets, "doc_id long, lang string, slots binary").where("slots IS NOT NULL").collect()  # at most 4 * SLOTS bytes each
    rows.sort(key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0, r["lang"], r["slots"]))
    return [np.frombuffer(r["slots"], np.int32) for r in rows], [r["lang"] for r in rows]


def predict(docs: DataFrame, model: KernelRidge | None) -> DataFrame:
    """(doc_id, text) -> doc_id, lang_pred, score."""

    def make():
        def work(batch):
            texts = batch.column(1).to_pylist()
            known = [i for i, t in enumerate(texts) if has_letter(t)]
            names, sure = [UNDETERMINED] * len(texts), [1.0] * len(texts)
            if known:
                found = model.predict([texts[i] for i in known]) if model else ([UNDETERMINED] * len(known), [0.0] * len(known))
                for i, name, p in zip(known, *found):
                    names[i], sure[i] = name, p
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(sure, pa.float64())], ["doc_id", "lang_pred", "score"])

        return work

    return map_texts(docs.select("doc_id", F.col("text").cast("string").alias("text")), make, "doc_id long, lang_pred string, score double")


def classify(docs: DataFrame) -> DataFrame:
    """The result of op5: learns where crc32(doc_id) mod 5 is not 0."""
    model = fit(*training_rows(docs, crc_fold("doc_id", 5) != 0))
    found = predict(docs, model)
    return found.select("doc_id", F.coalesce(crc_fold("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "lang_pred", "score")


def keep_known(docs: DataFrame) -> DataFrame:
    """A filter: documents whose language is determined, all columns as they are."""
    model = fit(*training_rows(docs))
    at = docs.columns.index("text")

    def run(batches):
        for batch in text_slices(batches):
            texts = batch.column(at).to_pylist()
            known = pa.array([has_letter(t) for t in texts], pa.bool_())
            rows = batch.filter(known)
            if rows.num_rows and model:
                names, _ = model.predict(rows.column(at).to_pylist())
                yield rows.filter(pa.array([n != UNDETERMINED for n in names], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def query(spark, sf_dir):
    return classify(table(spark, sf_dir, "documents"))
