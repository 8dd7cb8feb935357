"""MinHash near-duplicates: improved consistent weighted sampling over TF-IDF shingles, banded, verified exactly.

Words are runs of letters and digits (ASCII, and all longer code points) of the lower-cased text; a shingle is five consecutive words (a text of one to four
words is one shingle). A shingle weighs its count times a damped inverse document frequency,
1 + log((1 + N) / (1 + df)) / log(1 + N). Document frequencies come from all documents, in a table of hashed counters of
fixed size from which the noise of a counter (its mean and three deviations) is taken off. Each document gets BANDS x ROWS samples; documents that agree in a
band are candidates, and links are pairs whose weighted Jaccard similarity, computed from all their shingles, reaches
the threshold.

Texts with equal shingles are one class, and buckets of the same classes are one bucket. A bucket that fits a block is
compared in full by one group, whose links come back as a spanning tree. In a larger one every class is compared with the
bucket's hub, again with other hubs while that joins components, and then all classes of different components with each
other, block by block. So every pair that agrees in a band is compared or of one component already, whatever the sizes.
Shingles are compared as 32-bit hashes.

Null and wordless texts link with nothing, nor do rows with a null doc_id. Rows of one id are one document: with
different texts it belongs to the classes of all of them, and its component is the least of theirs.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import keep_between_tasks, map_groups, map_texts, settle, table
from .components import components
from .repeats import Powers, mixed, segment_digests, sieve

SHINGLE = 5
THRESHOLD = 0.8
BANDS, ROWS = 16, 4
#: Counters of document frequencies, and the pieces they travel in.
COUNTERS, PIECES = 1 << 20, 64
#: Entries of the table of random variates that shingles are hashed into, anew for each sample.
VARIATES = 1 << 14
#: Classes and packed bytes that one group takes: a bucket, or a block of a larger one; columns of a product that are held at once.
BLOCK, BLOCK_BYTES, COLUMNS = 256, 1 << 20, 1024
#: Another round of hubs is made where the last one left less than this share of the open pairs.
PROGRESS = 0.75
#: Weights are rounded to this many steps an octave when samples are drawn (not when a pair is verified).
OCTAVE, GRID = 8, 112
#: Samples times shingles that are drawn at once.
DRAWN = 1 << 20
# The bytes of words in lower-cased UTF-8: digits, a to z, and all of longer code points.
_WORD_BYTE = np.zeros(256, bool)
_WORD_BYTE[48:58] = _WORD_BYTE[97:123] = _WORD_BYTE[128:] = True


def make_shingles():
    powers = Powers()

    def shingles(text: str | None) -> np.ndarray:
        """32-bit hashes of the shingles of a text, with repeats."""
        raw = np.frombuffer((text or "").lower().encode(), np.uint8)
        inside = np.zeros(len(raw) + 2, bool)
        inside[1:-1] = _WORD_BYTE[raw]
        border = np.flatnonzero(inside[1:] != inside[:-1])
        begin, end = border[0::2], border[1::2]
        n = min(SHINGLE, len(begin))
        if not n:
            return np.zeros(0, np.uint64)
        h = segment_digests(raw, begin, end, powers)
        out = h[: len(h) - n + 1].copy()
        for k in range(1, n):
            out = out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(h) - n + 1 + k]
        return mixed(out) >> np.uint64(32)

    return shingles


def document_frequencies(docs: DataFrame) -> np.ndarray:
    """Damped inverse document frequencies by counter, from all documents."""

    def count(batches):
        shingles, counters, documents = make_shingles(), np.zeros(COUNTERS, np.uint32), 0
        for batch in batches:
            for text in batch.column(0).to_pylist():
                h = np.unique(shingles(text))
                if len(h):
                    documents += 1
                    np.add.at(counters, (h % COUNTERS).astype(np.int64), 1)
        if documents:
            pieces = np.split(counters, PIECES)
            yield pa.RecordBatch.from_arrays([pa.array(range(PIECES), pa.int32()), pa.array([p.tobytes() for p in pieces], pa.binary()), pa.array([documents] * PIECES, pa.int64())], ["piece", "counts", "documents"])

    def add(batches):
        total: dict[int, list] = {}
        for batch in batches:
            for piece, counts, documents in zip(*(c.to_pylist() for c in batch.columns)):
                x = np.frombuffer(counts, "<u4").astype(np.uint64)
                if piece in total:
                    total[piece][0] += x
                    total[piece][1] += documents
                else:
                    total[piece] = [x.copy(), documents]
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([t[0].tobytes() for t in total.values()], pa.binary()), pa.array([t[1] for t in total.values()], pa.int64())], ["piece", "counts", "documents"])

    kinds = "piece int, counts binary, documents long"
    rows = docs.select("text").mapInArrow(count, kinds).repartition(PIECES, "piece").mapInArrow(add, kinds).collect()  # PIECES rows
    counts, n = np.zeros(COUNTERS), 1
    for r in rows:
        size = COUNTERS // PIECES
        counts[r["piece"] * size : (r["piece"] + 1) * size] = np.frombuffer(r["counts"], "<u8")
        n = max(n, r["documents"])
    noise = counts.mean()
    counts = np.clip(counts - noise - 3 * np.sqrt(noise), 0, n)
    return (1 + np.log((1 + n) / (1 + counts)) / np.log(1 + n)).astype(np.float32)


class WeightedSampler:
    """Improved consistent weighted sampling with variates looked up by a hash of shingle and sample number.

    For a variate triple (r, c, beta) and weight w the sample's step is floor(log w / r + beta), and the shingle of least
    log c - r (step - beta) - r is drawn; steps and ranks of all triples are tabled for each weight of the grid.
    """

    def __init__(self, samples: int = BANDS * ROWS, seed: int = 7):
        g = np.random.default_rng(seed)
        r, log_c, beta = (x.astype(np.float32) for x in (g.gamma(2.0, 1.0, VARIATES), np.log(g.gamma(2.0, 1.0, VARIATES)), g.uniform(0, 1, VARIATES)))
        log_w = (np.arange(GRID)[:, None] * np.log(2) / OCTAVE).astype(np.float32)
        self.step = np.floor(log_w / r + beta).astype(np.int32)
        self.rank = (log_c - r * (self.step.astype(np.float32) - beta) - r).ravel()
        self.odd = g.integers(1, 1 << 62, samples, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def samples(self, shingle: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """One number a sample: two weighted sets agree in it with about the probability of their similarity."""
        row = np.clip(np.rint(np.log2(weight) * OCTAVE), 0, GRID - 1).astype(np.int64) * VARIATES
        spread, shift = mixed(shingle), np.uint64(64 - (VARIATES - 1).bit_length())
        out, at_once = np.empty(len(self.odd), np.uint64), max(1, DRAWN // len(shingle))
        for k in range(0, len(self.odd), at_once):
            odd = self.odd[k : k + at_once]
            at = ((spread[None, :] * odd[:, None]) >> shift).view(np.int64)
            at += row
            best = self.rank[at].argmin(1)
            drawn = at[np.arange(len(odd)), best]
            out[k : k + at_once] = shingle[best] * np.uint64(1 << 20) + (self.step.ravel()[drawn] & 0xFFFFF).astype(np.uint64)
        return mixed(out)


@lru_cache(maxsize=1)
def default_sampler() -> WeightedSampler:
    """One a worker process, until it serves another operator."""
    keep_between_tasks(__name__, default_sampler.cache_clear)
    return WeightedSampler()


def digest_of(sorted_hashes: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(sorted_hashes.tobytes()) - (1 << 63)


def weigh(hashes: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    shingle, count = np.unique(hashes, return_counts=True)
    return shingle, count * idf[(shingle % COUNTERS).astype(np.int64)]


def similarity(a: np.ndarray, b: np.ndarray, idf: np.ndarray) -> float:
    """Weighted Jaccard similarity of two arrays of shingle hashes with repeats."""
    (sa, wa), (sb, wb) = weigh(a, idf), weigh(b, idf)
    _, i, j = np.intersect1d(sa, sb, assume_unique=True, return_indices=True)
    low = np.minimum(wa[i], wb[j]).sum(dtype=np.float64)
    both = wa.sum(dtype=np.float64) + wb.sum(dtype=np.float64) - low
    return float(low / both) if both > 0 else 0.0


def signatures(docs: DataFrame, idf: np.ndarray) -> DataFrame:
    """doc_id, digest (of the shingles; null without any), bands, size (bytes of the packed shingles)."""
    broadcast = docs.sparkSession.sparkContext.broadcast(idf)

    def make():
        shingles, sampler, weights = make_shingles(), default_sampler(), broadcast.value

        def work(batch):
            digests, bands, sizes = [], [], []
            for text in batch.column(1).to_pylist():
                h = shingles(text)
                sizes.append(4 * len(h))
                if not len(h):
                    digests.append(None)
                    bands.append(None)
                    continue
                h = np.sort(h)
                digests.append(digest_of(h))
                rows = sampler.samples(*weigh(h, weights)).reshape(BANDS, ROWS)
                key = mixed(rows[:, 0])
                for k in range(1, ROWS):
                    key = mixed(key * np.uint64(31) + rows[:, k])
                key = mixed(key + np.arange(BANDS, dtype=np.uint64))
                bands.append(key.view(np.int64).tolist())
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sizes, pa.int64())], ["doc_id", "digest", "bands", "size"])

        return work

    return map_texts(docs.select("doc_id", F.col("text").cast("string").alias("text")), make, "doc_id long, digest long, bands array<bigint>, size long")


def vectors(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """digest, shingles (sorted 32-bit hashes, packed) of the classes that are wanted (node, digest)."""

    def make():
        shingles = make_shingles()

        def work(batch):
            rows = [np.sort(shingles(t)) for t in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array([digest_of(r) for r in rows], pa.int64()), pa.array([r.astype("<u4").tobytes() for r in rows], pa.binary())], ["node", "digest", "shingles"])

        return work

    some = docs.where(sieve(wanted.select(F.col("node").alias("doc_id"))))
    found = map_texts(some.select("doc_id", F.col("text").cast("string").alias("text")), make, "node long, digest long, shingles binary")
    return found.join(wanted, ["node", "digest"]).groupBy("digest").agg(F.first("shingles").alias("shingles"))


class Occurrences:
    """The packed shingles of several classes as columns (shingle, how often before in the class), ordered by column."""

    def __init__(self, packed: list[bytes], idf: np.ndarray):
        lengths = [len(p) // 4 for p in packed]
        h, at = np.frombuffer(b"".join(packed), "<u4").astype(np.uint64), np.repeat(np.arange(len(packed)), lengths)
        first = np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (at[1:] != at[:-1])))) if len(h) else np.zeros(0, np.int64)
        before = np.arange(len(h)) - np.repeat(first, np.diff(first, append=len(h)))
        column, weight = (h << np.uint64(32)) + before.astype(np.uint64), idf[(h % COUNTERS).astype(np.int64)].astype(np.float64)
        self.total, order = np.bincount(at, weight, len(packed)), np.argsort(column, kind="stable")
        self.column, self.at, self.weight = column[order], at[order], weight[order]

    def dense(self, columns: np.ndarray, weighted: bool) -> np.ndarray:
        low, high = np.searchsorted(self.column, columns[0]), np.searchsorted(self.column, columns[-1], "right")
        spot = np.searchsorted(columns, self.column[low:high])
        held = columns[spot] == self.column[low:high]
        out = np.zeros((len(self.total), len(columns)))
        out[self.at[low:high][held], spot[held]] = self.weight[low:high][held] if weighted else 1
        return out


def similarities(a: Occurrences, b: Occurrences) -> np.ndarray:
    """Weighted Jaccard similarities of all classes of a with all of b: the lesser of two counts is the number of occurrences in both."""
    common = np.intersect1d(a.column, b.column)
    low = np.zeros((len(a.total), len(b.total)))
    for k in range(0, len(common), COLUMNS):
        columns = common[k : k + COLUMNS]
        low += a.dense(columns, True) @ b.dense(columns, False).T
    return low / (a.total[:, None] + b.total[None, :] - low)


def _alike(a: list[bytes], b: list[bytes], idf: np.ndarray, threshold: float) -> np.ndarray:
    """Which classes of a reach the threshold with which of b."""
    read = lambda p: np.frombuffer(p, "<u4").astype(np.uint64)
    if a is b and len(a) == 2:
        link = similarity(read(a[0]), read(a[1]), idf) >= threshold
        return np.array([[True, link], [link, True]])
    one = Occurrences(a, idf)
    near = similarities(one, one if a is b else Occurrences(b, idf))
    for i, j in np.argwhere(np.abs(near - threshold) < 1e-9):  # sums in another order must not decide
        near[i, j] = similarity(read(a[i]), read(b[j]), idf)
    return near >= threshold


def _tree(link: np.ndarray) -> np.ndarray:
    """For each of n classes the first one that links of a symmetric matrix lead to."""
    label = np.arange(len(link))
    while True:
        least = np.minimum(label, np.where(link, label[None, :], len(link)).min(1, initial=len(link)))
        least = least[least]
        if (least == label).all():
            return label
        label = least


_LINK = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _within(rows: DataFrame, known: DataFrame, idf: np.ndarray, threshold: float) -> DataFrame:
    """rows: key, node, digest, of buckets that fit a block. (a, b): links that span what the links of all pairs of a bucket connect."""
    broadcast = rows.sparkSession.sparkContext.broadcast(idf)

    def compare(_, members):
        members.sort()
        packed = [m[1] for m in members]
        root = _tree(_alike(packed, packed, broadcast.value, threshold))
        return [(members[r][0], members[k][0]) for k, r in enumerate(root.tolist()) if r != k]

    met = rows.select("key", "node", "digest").join(known, "digest").select("key", "node", "shingles")
    return map_groups(met, ["key"], compare, _LINK).where("a <> b")


def _hub_links(rows: DataFrame, known: DataFrame, idf: np.ndarray, threshold: float, seed: int) -> DataFrame:
    """rows: key, node, digest, component. (a, b): components that a class of one and the hub of its bucket, a class of the other, link."""
    broadcast = rows.sparkSession.sparkContext.broadcast(idf)
    order = F.struct((F.col("node") if not seed else F.xxhash64("node", F.lit(seed))).alias("o"), F.col("digest").alias("hub"), F.col("component").alias("a"))
    hubs = rows.groupBy("key").agg(F.min(order).alias("h")).select("key", "h.hub", "h.a")
    met = rows.select("key", "digest", F.col("component").alias("b")).join(hubs, "key").where("a <> b").select("hub", "digest", "a", "b").distinct()
    met = met.join(known, "digest").join(known.select(F.col("digest").alias("hub"), F.col("shingles").alias("of_hub")), "hub").select("a", "b", "of_hub", "shingles")

    def compare(batches):
        read = lambda p: np.frombuffer(p, "<u4").astype(np.uint64)
        for batch in batches:
            if batch.num_rows:
                near = [similarity(read(p), read(q), broadcast.value) >= threshold for p, q in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], schema=_LINK).filter(pa.array(near))

    return met.mapInArrow(compare, "a long, b long").distinct()


def _across(rows: DataFrame, known: DataFrame, idf: np.ndarray, threshold: float) -> DataFrame:
    """rows: key, node, digest, component, size. (a, b): components that any two classes of one bucket link.

    A bucket is dealt into blocks by hash, those of a component that fills one or more apart from the others; every two
    blocks meet in a task's group of bounded size, unless both are of one component.
    """
    broadcast = rows.sparkSession.sparkContext.broadcast(idf)
    share = F.greatest(F.count("*") / F.lit(BLOCK), F.sum("size") / F.lit(BLOCK_BYTES)).alias("share")
    shares = rows.groupBy("key", "component").agg(share).withColumn("owner", F.when(F.col("share") > 1, F.col("component").cast("string")).otherwise(""))
    shares = settle(shares)
    parts = settle(shares.groupBy("key", "owner").agg(F.ceil(F.sum("share")).alias("parts")))
    name = lambda part: F.concat_ws(":", "owner", part.cast("string")).alias("block")
    big = shares.where("owner <> ''").select("key", "component", "owner")
    dealt = rows.join(big, ["key", "component"], "left").withColumn("owner", F.coalesce("owner", F.lit(""))).join(parts, ["key", "owner"])
    dealt = dealt.select("key", "node", "digest", "component", name(F.pmod(F.xxhash64("digest"), F.col("parts"))))
    blocks = parts.select("key", "owner", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part")).select("key", "owner", name(F.col("part")))
    x, y = blocks.toDF("key", "owner_x", "x"), blocks.toDF("key", "owner_y", "y")
    meetings = x.join(y, "key").where((F.col("x") <= F.col("y")) & ((F.col("owner_x") != F.col("owner_y")) | (F.col("owner_x") == "")))
    ends = meetings.select("key", "x", "y", F.explode(F.array_distinct(F.array("x", "y"))).alias("block"))
    met = dealt.join(ends, ["key", "block"]).join(known, "digest").select("key", "x", "y", (F.col("block") == F.col("y")).alias("second"), "component", "shingles")

    def compare(key, members):
        one = [m for m in members if not m[0]]
        two = [m for m in members if m[0]] if key[1] != key[2] else members
        one = two if key[1] == key[2] else one
        if not one or not two:
            return []
        a = [m[2] for m in one]
        link = _alike(a, a if one is two else [m[2] for m in two], broadcast.value, threshold)
        return {(min(one[i][1], two[j][1]), max(one[i][1], two[j][1])) for i, j in np.argwhere(link).tolist() if one[i][1] != two[j][1]}

    return map_groups(met, ["key", "x", "y"], compare, _LINK).distinct()


def _renamed(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (node, component) after links between components; nodes that no label has yet are their own."""
    new = components(links)
    nodes = labels.unionAll(new.select("node", F.col("node").alias("component"))).groupBy("node").agg(F.min("component").alias("component"))
    return settle(nodes.join(new.toDF("component", "now"), "component", "left").select("node", F.coalesce("now", "component").alias("component")))


def grouped(docs: DataFrame, threshold: float = THRESHOLD, block: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(classes, labels): doc_id, digest, node (the least document of equal shingles); node, component for nodes with a link.

    Components are those of all pairs that agree in a band and reach the threshold: each such pair is compared, or both
    are known to be of one component. block: classes that a group takes, for tests (any gives the same components).
    """
    idf = document_frequencies(docs)
    signed = settle(signatures(docs, idf))
    usable = signed.where(F.col("doc_id").isNotNull() & F.col("digest").isNotNull())
    classes = settle(usable.groupBy("digest").agg(F.min("doc_id").alias("node"), F.first("size").alias("size"), F.first("bands").alias("bands")))
    keyed = classes.select("node", "digest", "size", F.explode("bands").alias("key"))
    mark = lambda seed: F.bit_xor(F.xxhash64("digest", F.lit(seed))).alias(f"m{seed}")
    full = keyed.groupBy("key").agg(F.count("*").alias("n"), F.sum("size").alias("bytes"), mark(1), mark(2)).where("n > 1")
    full = full.groupBy("n", "bytes", "m1", "m2").agg(F.min("key").alias("key"))  # buckets of the same classes are one
    rows = settle(keyed.join(full.select("key", "n", "bytes"), "key").select("key", "node", "digest", "size", "n", "bytes"))
    known = settle(vectors(docs, rows.select("node", "digest").distinct()))
    fits = (F.col("n") <= (block or BLOCK)) & (F.col("bytes") <= BLOCK_BYTES)
    labels = settle(components(_within(rows.where(fits), known, idf, threshold)))
    wide, turn, before = rows.where(~fits), 0, None
    while True:
        placed = wide.join(labels, "node", "left").select("key", "node", "digest", "size", F.coalesce("component", "node").alias("component"))
        sizes = placed.groupBy("key", "component").agg(F.count("*").cast("double").alias("n")).groupBy("key").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("same"))
        open_ = settle(sizes.where("n * n > same").select("key", "n", ((F.col("n") * F.col("n") - F.col("same")) / 2).alias("cross")))
        left = open_.agg(F.count("*").alias("buckets"), F.sum("n").alias("n"), F.sum("cross").alias("cross")).first()
        if not left["buckets"]:
            return usable.select("doc_id", "digest").join(classes.select("digest", "node"), "digest"), labels
        placed = settle(placed.join(open_.select("key"), "key"))
        # hubs make a family one component for a comparison a class; they go on while that pays, and the rest is compared in full
        worth = left["cross"] > BLOCK * left["n"] and (before is None or left["cross"] < before * PROGRESS)
        found = settle(_hub_links(placed, known, idf, threshold, turn) if worth else _across(placed, known, idf, threshold))
        labels = _renamed(labels, found)
        if not worth:
            return usable.select("doc_id", "digest").join(classes.select("digest", "node"), "digest"), labels
        turn, before = turn + 1, left["cross"]


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row a row of docs: doc_id, class_id (least document of equal shingles), component_id, kept (it is the least of its component)."""
    classes, labels = grouped(docs, threshold)
    return _judged(docs, classes, labels)


def _judged(docs: DataFrame, classes: DataFrame, labels: DataFrame) -> DataFrame:
    found = classes.join(labels, "node", "left").groupBy("doc_id").agg(F.min("node").alias("class_id"), F.min(F.coalesce("component", "node")).alias("component_id"))
    out = docs.select("doc_id").join(found, "doc_id", "left")
    component = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_first(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs with the least document of every group of near-duplicates; all columns as they are."""
    gone = near_duplicates(docs, threshold).where(~F.col("kept")).select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"] == F.col("_gone"), "left_anti")


def query(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"))
