"""Benchmark decontamination with DataFrame functions only.

Words are runs of [0-9a-z] and of code points from U+0080 on, after A-Z are lower-cased. The windows of the benchmark
(WINDOW consecutive words of an item; a shorter item that has words is one window) make two broadcast structures: a hash
set as a bitmap, which every window of the documents is tested against inside its row, and the windows' exact texts,
which what passes is joined with. So no text is shuffled, and a hit is always an equal text, never an equal hash.

Null texts have no words. Items without words have no windows; a window that several items share counts for each. Every
row of the documents gives one row of the report; rows with the same doc_id and text are judged once, and a doc_id with
several texts has each judged on its own. Columns other than doc_id and text are left alone. With an empty benchmark
nothing is hit.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import table

WINDOW = 10
#: Up to so many windows their texts are broadcast for the exact join; beyond, what passed the bitmap is shuffled to them.
BROADCAST_WINDOWS = 1_000_000
#: Bits of the bitmap for each window, and its largest size (of 64-bit words, 8 MB: 16 bits a window of four million).
BITS_PER_WINDOW, MOST_LONGS = 128, 1 << 20
# What is not a word, before and after lower-casing.
_NOT_WORD = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), _NOT_WORD), lambda w: w != "")


def _marks(word_list: Column) -> Column:
    """A hash of each word, blind to case (wider than A-Z, which only lets more pass to the exact test)."""
    return F.transform(word_list, lambda w: F.xxhash64(F.lower(w)))


def _key(marks: Column, i: Column, length: int) -> Column:
    """Mixes the first, a middle and the last word of the window at i."""
    at = lambda k: F.get(marks, i + k)
    return F.abs(at(0).bitwiseXOR(F.shiftleft(at(length // 2), 1)).bitwiseXOR(F.shiftleft(at(length - 1), 2)).bitwiseXOR(F.lit(length)) % (1 << 40))


def _gram(word_list: Column, i: Column, length: int) -> Column:
    return F.translate(F.array_join(F.slice(word_list, i + 1, length), " "), _UPPER, _LOWER)


def _starts(count: Column, length: int) -> Column:
    return F.when(count >= length, F.sequence(F.lit(0), count - length)).otherwise(F.array().cast("array<int>"))


def benchmark_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """item_id, length, key, gram: distinct windows of all items."""
    listed = benchmark.select("item_id", words(F.col("text")).alias("words")).withColumn("n", F.size("words")).where(F.col("n") > 0).withColumn("marks", _marks(F.col("words")))

    def shape(n: int) -> Column:
        fits = F.col("n") == n if n < window else F.col("n") >= n
        starts = F.when(fits, _starts(F.col("n"), n)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.struct(F.lit(n).alias("length"), _key(F.col("marks"), i, n).alias("key"), _gram(F.col("words"), i, n).alias("gram")))

    shapes = [shape(n) for n in range(1, window + 1)]
    return listed.select("item_id", F.explode(F.concat(*shapes)).alias("w")).select("item_id", "w.*").distinct()


def _bitmap(known: DataFrame, length: int, count: int) -> tuple[Column, int]:
    """The keys of windows of a length as a constant array of 64-bit words, MOST_LONGS at most, and their number."""
    longs = 16
    while longs < MOST_LONGS and longs * 64 < BITS_PER_WINDOW * count:
        longs *= 2
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("key").bitwiseAND(63).cast("int"))
    words = known.where(F.col("length") == length).groupBy((F.shiftright("key", 6) % longs).cast("int").alias("k")).agg(F.bit_or(bit).alias("v"))
    bits = [0] * longs
    for r in words.collect():  # at most `longs` rows
        bits[r["k"]] = r["v"]
    return F.from_json(F.lit(f"[{','.join(map(str, bits))}]"), "array<bigint>"), longs


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """One row a document (by doc_id and text): doc_id, digest (of the text), copies (rows with both), n_words, spans (array
    of start, end in words), items (sorted ids as text)."""
    known = benchmark_windows(benchmark, window).persist()
    try:
        shapes = {r["length"]: r["n"] for r in known.groupBy("length").agg(F.count("*").alias("n")).collect()}  # `window` rows
        maps = {n: _bitmap(known, n, shapes[n]) for n in sorted(shapes)}
    finally:
        known.unpersist()
    listed = docs.select("doc_id", F.xxhash64(F.col("text")).alias("digest"), words(F.col("text")).alias("words"))
    listed = listed.select("*", F.size("words").cast("long").alias("n_words"), _marks(F.col("words")).alias("marks"))

    def candidates(n: int) -> Column:
        bits, longs = maps[n]

        def passes(i):
            key = _key(F.col("marks"), i, n)
            word = F.get(bits, (F.shiftright(key, 6) % longs).cast("int"))
            return F.call_function("getbit", word, key.bitwiseAND(F.lit(63)).cast("int")) == 1

        starts = F.filter(_starts(F.size("words"), n), passes)
        return F.transform(starts, lambda i: F.struct(i.alias("start"), F.lit(n).alias("length"), _gram(F.col("words"), i, n).alias("gram")))

    found = [candidates(n) for n in sorted(shapes)]
    none = F.array().cast("array<struct<start:int,length:int,gram:string>>")
    tried = listed.select("doc_id", "digest", "n_words", F.posexplode_outer(reduce(F.concat, found, none)).alias("p", "c")).select("doc_id", "digest", "n_words", "p", "c.start", "c.length", "c.gram")
    exact = known.groupBy("length", "gram").agg(F.collect_set(F.col("item_id").cast("string")).alias("own"))
    joined = tried.join(F.broadcast(exact) if sum(shapes.values()) <= BROADCAST_WINDOWS else exact, ["length", "gram"], "left")
    true_hit = F.col("own").isNotNull()
    return joined.groupBy("doc_id", "digest").agg(
        F.sum((F.coalesce("p", F.lit(0)) == 0).cast("int")).alias("copies"),
        F.max("n_words").alias("n_words"),
        F.array_sort(F.collect_set(F.when(true_hit, F.struct(F.col("start"), (F.col("start") + F.col("length")).alias("end"))))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("own")))).alias("items"),
    )


def covered(spans: Column) -> Column:
    """How many positions a sorted list of spans (start, end) covers."""
    zero = F.struct(F.lit(0).alias("sum"), F.lit(0).alias("upto"))
    step = lambda a, s: F.struct((a["sum"] + F.greatest(F.lit(0), s["end"] - F.greatest(a["upto"], s["start"]))).alias("sum"), F.greatest(a["upto"], s["end"]).alias("upto"))
    return F.aggregate(spans, zero, step, lambda a: a["sum"])


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The result of op1."""
    out = hits(docs, benchmark).withColumn("n_hit", covered(F.col("spans")).cast("long"))
    out = out.withColumn("_copy", F.explode(F.sequence(F.lit(1), "copies")))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def _marked(docs: DataFrame, found: DataFrame, how: str) -> DataFrame:
    """docs joined with rows of `hits` that have spans, by doc_id and text; nulls are equal."""
    few = found.where(F.size("spans") > 0).select(F.col("doc_id").alias("_id"), F.col("digest").alias("_digest"), "spans")
    return docs.join(few, F.col("_id").eqNullSafe(docs["doc_id"]) & (F.col("_digest") == F.xxhash64(docs["text"])), how)


def remove_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without those that hold a benchmark window; all columns as they are, null ids included."""
    return _marked(docs, hits(docs, benchmark), "left_anti")


def remove_spans(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, text: the words outside all hits joined by a space; documents without a hit keep their text."""
    inside = lambda k: F.exists("_spans", lambda s: (s["start"] <= k) & (k < s["end"]))
    rest = F.array_join(F.filter(words(F.col("text")), lambda w, k: ~inside(k)), " ")
    met = _marked(docs.select("doc_id", "text"), hits(docs, benchmark), "left").withColumnRenamed("spans", "_spans")
    return met.select("doc_id", F.when(F.col("_spans").isNull(), F.col("text")).otherwise(rest).alias("text"))


def query(spark, sf_dir):
    return report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


ORACLE_SQL = r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
bw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bg AS (SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i:i + least(10, len(w)) - 1], ' ') AS gram
       FROM (SELECT item_id, w, unnest(range(1, 2 + greatest(0, len(w) - 10))) AS i FROM bw WHERE len(w) > 0)),
lens AS (SELECT DISTINCT n FROM bg),
dg AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS gram
       FROM (SELECT doc_id, w, n, unnest(range(1, 2 + len(w) - n)) AS i FROM dw, lens WHERE len(w) >= n)),
hit AS (SELECT doc_id, dg.n, i, item_id FROM dg JOIN bg ON dg.n = bg.n AND dg.gram = bg.gram),
pos AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(x, ',' ORDER BY x)) AS sha FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM hit) GROUP BY doc_id)
SELECT dw.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       coalesce(sha, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN pos ON dw.doc_id = pos.doc_id LEFT JOIN its ON dw.doc_id = its.doc_id
"""
