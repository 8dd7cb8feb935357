"""Chunked ordered sets: one row a chunk.

A set belongs to an `owner`. Its heads are the elements whose hash is 0 modulo b; a head's tail are the elements up to
the next head; elements before the first head are the prefix (head is null). Heads depend on the element alone, so the
layout of a set does not depend on how it came about, and what a recursive split would look for is a join.

chunk rows: owner, head, lo, hi, cnt (tail without its head), elems (sorted), and with values vals (aligned), agg. In
place of elems a chunk may hold its tail coded (see `codec`); operations take any codec, open the rows they have chosen,
and give rows of the same codec back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codec import COLUMNS, codec_of, coded, opened
from ..functions.hashing import is_head

DEFAULT_B = 256
_FOLDS = {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count}
#: How values that are folded already are folded again.
_AGAIN = {"count": "sum"}


def fold(df: DataFrame, combine: str = "last", order: str | None = None) -> DataFrame:
    """(owner, elem[, val]) with each element once, values folded; rows without an owner or element go.

    last and first go by the column `order`; without one there is no order among rows, and the largest (least) value counts.
    """
    df = df.where("owner IS NOT NULL AND elem IS NOT NULL")
    if "val" not in df.columns:
        return df.select("owner", "elem").distinct()
    value = _FOLDS[combine]("val") if combine in _FOLDS else (F.max_by if combine == "last" else F.min_by)("val", order or "val")
    return df.groupBy("owner", "elem").agg(value.alias("val"))


def assign_heads(entries: DataFrame, b: int = DEFAULT_B, seed: int = 0, span: int | None = None) -> DataFrame:
    """entries with `head`. With span, an owner's elements are dealt by ranges of that width, so that the largest owner
    is no single task: each range looks up its own heads, and what precedes them comes from the ranges before."""
    own = F.when(is_head(F.col("elem"), b, seed), F.col("elem"))
    if span is None:
        return entries.withColumn("head", F.last(own, ignorenulls=True).over(Window.partitionBy("owner").orderBy("elem")))
    dealt = entries.withColumn("_range", F.floor(F.col("elem") / span))
    near = dealt.withColumn("head", F.last(own, ignorenulls=True).over(Window.partitionBy("owner", "_range").orderBy("elem")))
    tops = dealt.groupBy("owner", "_range").agg(F.max(own).alias("_top"))
    before = Window.partitionBy("owner").orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    carried = tops.withColumn("_carry", F.last("_top", ignorenulls=True).over(before)).drop("_top")
    return near.join(carried, ["owner", "_range"]).withColumn("head", F.coalesce("head", "_carry")).drop("_range", "_carry")


def rechunk(assigned: DataFrame) -> DataFrame:
    """(owner, head, elem[, val]) -> chunk rows."""
    tail = F.col("head").isNull() | (F.col("elem") != F.col("head"))
    aggregates = [F.min(F.when(tail, F.col("elem"))).alias("lo"), F.max(F.when(tail, F.col("elem"))).alias("hi"), F.count(F.when(tail, 1)).cast("int").alias("cnt")]
    if "val" not in assigned.columns:
        return assigned.groupBy("owner", "head").agg(*aggregates, F.sort_array(F.collect_list(F.when(tail, F.col("elem")))).alias("elems"))
    pairs = F.sort_array(F.collect_list(F.when(tail, F.struct("elem", "val"))))
    out = assigned.groupBy("owner", "head").agg(*aggregates, pairs.alias("_p"), F.max(F.when(~tail, F.col("val"))).alias("head_val"), F.sum("val").alias("agg"))
    return out.select("owner", "head", "lo", "hi", "cnt", F.col("_p.elem").alias("elems"), F.col("_p.val").alias("vals"), "head_val", "agg")


def build(df: DataFrame, b: int = DEFAULT_B, seed: int = 0, combine: str = "last", order: str | None = None, span: int | None = None, codec: str = "plain") -> DataFrame:
    """Sets from (owner, elem[, val]) rows in any order, with duplicates."""
    return coded(rechunk(assign_heads(fold(df, combine, order), b, seed, span)), codec)


def entries(chunks: DataFrame) -> DataFrame:
    """(owner, head, elem[, val]): every element with its chunk."""
    chunks = opened(chunks)
    if "vals" in chunks.columns:
        tail = F.arrays_zip(F.col("elems").alias("elem"), F.col("vals").alias("val"))
        own = F.when(F.col("head").isNotNull(), F.array(F.struct(F.col("head").alias("elem"), F.col("head_val").alias("val"))))
        both = F.concat(F.coalesce(own, F.slice(tail, 1, 0)), tail)
        return chunks.select("owner", "head", F.explode(both).alias("e")).select("owner", "head", "e.elem", "e.val")
    return chunks.select("owner", "head", F.explode(all_elems()).alias("elem"))


def all_elems() -> Column:
    """The chunk's elements, head included, in order."""
    return F.when(F.col("head").isNull(), F.col("elems")).otherwise(F.concat(F.array("head"), F.col("elems")))


def locate_chunk(chunks: DataFrame, probes: DataFrame) -> DataFrame:
    """probes (owner, e, ...) with `found_head`: the head of the chunk that e falls in (null: the prefix). Heads of owners
    that are not asked about are left where they are."""
    kept = [c for c in probes.columns if c not in ("owner", "e")]
    marks = chunks.where(F.col("head").isNotNull()).join(probes.select("owner").distinct(), "owner", "left_semi").select("owner", F.col("head").alias("e"), F.lit(0).alias("_kind"), *(F.lit(None).cast(probes.schema[c].dataType).alias(c) for c in kept))
    asked = probes.select("owner", "e", F.lit(1).alias("_kind"), *kept)
    w = Window.partitionBy("owner").orderBy("e", "_kind")
    head = F.last(F.when(F.col("_kind") == 0, F.col("e")), ignorenulls=True).over(w)
    return marks.unionByName(asked).withColumn("found_head", head).where(F.col("_kind") == 1).drop("_kind")


def find(chunks: DataFrame, probes: DataFrame) -> DataFrame:
    """probes with `pred`: the largest element that is at most e, null where there is none."""
    at = locate_chunk(chunks, probes)
    tail = COLUMNS[codec_of(chunks)]
    side = chunks.select(F.col("owner").alias("_o"), F.col("head").alias("_h"), tail)
    met = at.join(side, (F.col("owner") == F.col("_o")) & F.col("found_head").eqNullSafe(F.col("_h")), "left")
    met = opened(met)
    below = F.array_max(F.filter("elems", lambda x: x <= F.col("e")))
    return met.withColumn("pred", F.coalesce(below, "found_head")).drop("_o", "_h", "elems", "found_head")


def contains(chunks: DataFrame, probes: DataFrame) -> DataFrame:
    return find(chunks, probes).withColumn("present", F.coalesce(F.col("pred") == F.col("e"), F.lit(False))).drop("pred")


def map_elems(chunks: DataFrame, f) -> DataFrame:
    """f applied to every element: (owner, elem, mapped). The result is no set until it is built again."""
    return entries(chunks).select("owner", "elem", f(F.col("elem")).alias("mapped"))


# ------------------------------------------------------------------------------------------------------- set operations


def _marked(delta: DataFrame, columns: list[str]) -> DataFrame:
    return delta.select("owner", F.col("elem").alias("e"), *columns)


def touched(chunks: DataFrame, delta: DataFrame, b: int, seed: int = 0, removing: bool = False) -> DataFrame:
    """(owner, head) of the chunks that a delta (owner, elem) changes. When heads go, the chunk that takes over their
    tail (of the nearest head below that stays, or the prefix) is touched too."""
    hit = locate_chunk(chunks, _marked(delta, [])).select("owner", F.col("found_head").alias("head")).distinct()
    if not removing:
        return hit
    gone = delta.where(is_head(F.col("elem"), b, seed)).select("owner", F.col("elem").alias("head")).distinct().withColumn("_gone", F.lit(True))
    heads = chunks.where(F.col("head").isNotNull()).select("owner", "head").join(gone.select("owner").distinct(), "owner", "left_semi").join(gone, ["owner", "head"], "left")
    w = Window.partitionBy("owner").orderBy("head").rowsBetween(Window.unboundedPreceding, -1)
    heir = heads.withColumn("heir", F.last(F.when(F.col("_gone").isNull(), F.col("head")), ignorenulls=True).over(w)).where(F.col("_gone").isNotNull())
    return hit.unionByName(heir.select("owner", F.col("heir").alias("head"))).distinct()


def _split_touched(chunks: DataFrame, hit: DataFrame) -> tuple[DataFrame, DataFrame]:
    side = hit.select(F.col("owner").alias("_o"), F.col("head").alias("_h"))
    same = (F.col("owner") == F.col("_o")) & F.col("head").eqNullSafe(F.col("_h"))
    return chunks.join(side, same, "left_semi"), chunks.join(side, same, "left_anti")


def union(a: DataFrame, delta: DataFrame, b: int = DEFAULT_B, seed: int = 0, combine: str = "last") -> DataFrame:
    """Chunked set a with the entries of delta (owner, elem[, val], each element once); values of both sides are folded
    (last: delta's; count: counts are added).

    Only chunks that the delta touches are opened; a new head cuts its chunk. The others pass as they are.
    """
    changed, same = _split_touched(a, touched(a, delta, b, seed))
    inside = entries(changed).drop("head")
    if "vals" in a.columns:
        both = inside.withColumn("_side", F.lit(0)).unionByName(delta.select("owner", "elem", "val").withColumn("_side", F.lit(1)))
        merged = fold(both, _AGAIN.get(combine, combine), "_side")
    else:
        merged = inside.unionByName(delta.select("owner", "elem")).distinct()
    # an opened chunk starts at its own head, so the last head at or before an element is among the opened elements
    return same.unionByName(coded(rechunk(assign_heads(merged, b, seed)), codec_of(a)))


def difference(a: DataFrame, delta: DataFrame, b: int = DEFAULT_B, seed: int = 0) -> DataFrame:
    """Chunked set a without the elements of delta. A chunk whose head goes is handed to the head before it."""
    changed, same = _split_touched(a, touched(a, delta, b, seed, removing=True))
    left = entries(changed).drop("head").join(delta.select("owner", "elem").distinct(), ["owner", "elem"], "left_anti")
    return same.unionByName(coded(rechunk(assign_heads(left, b, seed)), codec_of(a)))


def intersect(a: DataFrame, c: DataFrame, combine: str = "last") -> DataFrame:
    """Common elements. Heads of the result are the heads that both have, so tails are joined again by their last head.
    Where both sides have values these are folded (last: c's); where only a has, its own stay."""
    left, right = entries(a).drop("head"), entries(c).drop("head")
    if "val" not in left.columns or "val" not in right.columns:
        both = left.join(right.select("owner", "elem"), ["owner", "elem"], "left_semi")
    else:
        met = left.join(right.withColumnRenamed("val", "_other"), ["owner", "elem"])
        how = {"sum": F.col("val") + F.col("_other"), "count": F.col("val") + F.col("_other"), "min": F.least("val", "_other"), "max": F.greatest("val", "_other"), "last": F.col("_other"), "first": F.col("val")}
        both = met.select("owner", "elem", how[combine].alias("val"))
    heads = a.where(F.col("head").isNotNull()).select("owner", F.col("head").alias("elem")).withColumn("_own", F.col("elem"))
    w = Window.partitionBy("owner").orderBy("elem")
    return coded(rechunk(both.join(heads, ["owner", "elem"], "left").withColumn("head", F.last("_own", ignorenulls=True).over(w)).drop("_own")), codec_of(a))


def multi_insert(a: DataFrame, batch: DataFrame, b: int = DEFAULT_B, seed: int = 0, combine: str = "last", order: str | None = None) -> DataFrame:
    """batch: owner, elem[, val], elements repeated in any way; its own values are folded first, by `order` for last and first."""
    return union(a, fold(batch, combine, order), b, seed, combine)


def multi_delete(a: DataFrame, batch: DataFrame, b: int = DEFAULT_B, seed: int = 0) -> DataFrame:
    return difference(a, batch, b, seed)


def union_prefix(prefixes: DataFrame, chunks: DataFrame, b: int = DEFAULT_B, seed: int = 0) -> DataFrame:
    """Union where one side consists of prefixes only (no heads): its elements go to prefixes and tails, none becomes a head."""
    at = locate_chunk(chunks, _marked(entries(prefixes), [])).select("owner", F.col("found_head").alias("head"), F.col("e").alias("elem"))
    changed, same = _split_touched(chunks, at.select("owner", "head").distinct())
    return same.unionByName(coded(rechunk(entries(changed).unionByName(at).distinct()), codec_of(chunks)))


def split(chunks: DataFrame, k: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(chunks below k, owners that hold k, chunks above k). Only chunks that straddle k are cut; what is above k in a cut
    chunk has lost its head and is a prefix."""
    first, last = F.coalesce("head", "lo"), F.coalesce("hi", "head")
    low = chunks.where(last < k)
    high = chunks.where(first > k)
    cut = chunks.where((first <= k) & (last >= k))
    inside, how = entries(cut), codec_of(chunks)
    below = coded(rechunk(inside.where(F.col("elem") < k)), how)
    above = coded(rechunk(inside.where(F.col("elem") > k).withColumn("head", F.lit(None).cast("long"))), how)
    return low.unionByName(below), inside.where(F.col("elem") == k).select("owner").distinct(), high.unionByName(above)


def smallest_head(chunks: DataFrame) -> DataFrame:
    return chunks.groupBy("owner").agg(F.min("head").alias("smallest_head"))


def concat_sets(left: DataFrame, middle: DataFrame, right: DataFrame, b: int = DEFAULT_B, seed: int = 0) -> DataFrame:
    """left < middle (owner, elem) < right in every owner, else a ValueError. The middle and the right side's prefix join
    the left's last chunk."""
    bounds = lambda df, low, high, name: df.groupBy("owner").agg(F.min(low).alias(f"{name}_low"), F.max(high).alias(f"{name}_high"))
    first, last = F.coalesce("head", "lo"), F.coalesce("hi", "head")
    met = bounds(left, first, last, "l").join(bounds(middle, "elem", "elem", "m"), "owner", "full").join(bounds(right, first, last, "r"), "owner", "full")
    crossed = (F.col("l_high") >= F.col("m_low")) | (F.col("m_high") >= F.col("r_low")) | (F.col("l_high") >= F.col("r_low"))
    if met.where(crossed).take(1):
        raise ValueError("the sets to concatenate overlap")
    loose = entries(right.where(F.col("head").isNull())).drop("head").unionByName(middle.select("owner", "elem"))
    fixed = right.where(F.col("head").isNotNull())
    return union(left, loose, b, seed).unionByName(fixed)


def expose(chunks: DataFrame) -> DataFrame:
    """(owner, root): the head that splits an owner's heads evenly, as the root of a balanced tree would; for tracing."""
    w = Window.partitionBy("owner")
    ranked = chunks.where(F.col("head").isNotNull()).select("owner", "head", F.row_number().over(w.orderBy("head")).alias("r"), F.count("*").over(w).alias("n"))
    return ranked.where(F.col("r") == F.floor(F.col("n") / 2) + 1).select("owner", F.col("head").alias("root"))


# -------------------------------------------------------------------------------------------------- sizes, ranks, ranges


def weight() -> Column:
    """Elements of a chunk, its head included."""
    return F.col("cnt") + F.col("head").isNotNull().cast("int")


def size(chunks: DataFrame) -> DataFrame:
    return chunks.groupBy("owner").agg(F.sum(weight()).cast("long").alias("size"))


def select_kth(chunks: DataFrame, k: int) -> DataFrame:
    """(owner, elem): the k-th smallest element, from 1; running sums over chunks find the chunk to open."""
    w = Window.partitionBy("owner").orderBy(F.col("head").asc_nulls_first())
    counted = chunks.withColumn("upto", F.sum(weight()).over(w)).withColumn("before", F.col("upto") - weight())
    return opened(counted.where((F.col("before") < k) & (F.col("upto") >= k))).select("owner", F.element_at(all_elems(), (F.lit(k) - F.col("before")).cast("int")).alias("elem"))


def rank(chunks: DataFrame, probes: DataFrame) -> DataFrame:
    """probes (owner, e) with `rank`: elements below e. The chunk of each probe alone is opened; what lies before it is
    a running sum of chunk sizes."""
    w = Window.partitionBy("owner").orderBy(F.col("head").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
    before = chunks.select("owner", "head", COLUMNS[codec_of(chunks)], F.coalesce(F.sum(weight()).over(w), F.lit(0)).alias("_before"))
    side = before.withColumnsRenamed({"owner": "_o", "head": "_h"})
    known = chunks.select("owner").distinct()
    at = locate_chunk(chunks, probes.select("owner", "e").distinct().join(known, "owner", "left_semi"))
    met = opened(at.join(side, (F.col("owner") == F.col("_o")) & F.col("found_head").eqNullSafe(F.col("_h")), "left"))
    inside = F.size(F.filter(F.coalesce("elems", F.array().cast("array<bigint>")), lambda x: x < F.col("e"))) + F.coalesce((F.col("found_head") < F.col("e")).cast("int"), F.lit(0))
    return met.select("owner", "e", (F.coalesce("_before", F.lit(0)) + inside).cast("long").alias("rank"))


def range_agg(chunks: DataFrame, ranges: DataFrame) -> DataFrame:
    """ranges (owner, lo_bound, hi_bound) with `total`: sum of values in the closed range. Chunks inside it give their
    stored sum; only chunks at the border are opened."""
    met = chunks.join(ranges, "owner").withColumn("first", F.coalesce("head", "lo")).withColumn("last", F.coalesce("hi", "head"))
    met = opened(met.where((F.col("last") >= F.col("lo_bound")) & (F.col("first") <= F.col("hi_bound"))))
    inside = (F.col("first") >= F.col("lo_bound")) & (F.col("last") <= F.col("hi_bound"))
    within = lambda x: (x >= F.col("lo_bound")) & (x <= F.col("hi_bound"))
    tail = F.aggregate(F.filter(F.arrays_zip("elems", "vals"), lambda p: within(p["elems"])), F.lit(0.0), lambda s, p: s + p["vals"])
    own = F.when(F.col("head").isNotNull() & within(F.col("head")), F.col("head_val")).otherwise(F.lit(0.0))
    part = F.when(inside, F.col("agg")).otherwise(tail + own)
    return met.groupBy("owner", "lo_bound", "hi_bound").agg(F.sum(part).alias("total"))


def range_scan(chunks: DataFrame, low: int, high: int) -> DataFrame:
    near = chunks.where((F.coalesce("hi", "head") >= low) & (F.coalesce("head", "lo") <= high))
    return entries(near).where(F.col("elem").between(low, high)).select("owner", "elem")


def min_max(chunks: DataFrame) -> DataFrame:
    """(owner, least, most) from the chunks' bounds alone."""
    return chunks.groupBy("owner").agg(F.min(F.coalesce("head", "lo")).alias("least"), F.max(F.coalesce("hi", "head")).alias("most"))


def first_elements(chunks: DataFrame, k: int) -> DataFrame:
    """The k smallest elements of each owner, opening no more chunks than hold them."""
    w = Window.partitionBy("owner").orderBy(F.col("head").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
    near = chunks.withColumn("before", F.coalesce(F.sum(weight()).over(w), F.lit(0))).where(F.col("before") < k)
    return opened(near).select("owner", F.posexplode(all_elems()), "before").where(F.col("pos") + F.col("before") < k).select("owner", F.col("col").alias("elem"))


def chunk_stats(chunks: DataFrame) -> DataFrame:
    """One row: sets, heads, prefixes, elements, mean and largest tail, height of a balanced tree over the most heads of a set."""
    each = chunks.groupBy("owner").agg(F.count("head").alias("h"), F.sum(F.col("head").isNull().cast("long")).alias("p"), F.sum(weight()).alias("e"), F.max("cnt").alias("x"), F.sum("cnt").alias("t"))
    return each.agg(
        F.count("*").alias("sets"), F.sum("h").alias("heads"), F.sum("p").alias("prefixes"), F.sum("e").cast("long").alias("elements"), F.max("x").cast("long").alias("largest"),
        (F.sum("t") / F.sum(F.col("h") + F.col("p"))).alias("mean"), F.ceil(F.log2(F.max("h") + 1)).cast("int").alias("height"),
    )
