import random

import pytest
from pyspark.sql import functions as F

from chunkgraph.functions.hashing import portable_hash_int
from chunkgraph.operators import sets

SCHEMA = "owner long, elem long"


def chunks_of(entries, b):
    """Plain version: {(owner, head): [tail]}."""
    out = {}
    for owner in {o for o, _ in entries}:
        head = None
        for e in sorted({e for o, e in entries if o == owner}):
            if portable_hash_int(e) % b == 0:
                head = e
                out[owner, head] = []
            else:
                out.setdefault((owner, head), []).append(e)
    return out


def as_dict(chunks):
    return {(r["owner"], r["head"]): r["elems"] for r in chunks.select("owner", "head", "elems").collect()}


def frame(spark, entries):
    return spark.createDataFrame(list(entries), SCHEMA)


def heads_below(n, b):
    return [x for x in range(n) if portable_hash_int(x) % b == 0]


def cases(b):
    h = heads_below(60, b)
    plain = [x for x in range(60) if x not in h]
    yield set()
    yield {(1, plain[0])}
    yield {(1, x) for x in plain[:9]}
    yield {(1, h[0]), (1, h[0] + 1)}
    yield {(1, h[0])}
    yield {(1, h[0]), (1, h[1]), (2, plain[3])}
    yield {(1, x) for x in range(60)} | {(2, x) for x in plain[5:20]}


@pytest.mark.parametrize("b", [1, 4, 8, 1000])
def test_build_special_cases(spark, b):
    for entries in cases(4):
        assert as_dict(sets.build(frame(spark, entries), b)) == chunks_of(entries, b)


def test_span_gives_the_same_layout(spark):
    entries = {(o, random.Random(o).randrange(500) + k) for o in range(3) for k in range(200)}
    f = frame(spark, entries)
    assert as_dict(sets.build(f, 8, span=32)) == as_dict(sets.build(f, 8)) == chunks_of(entries, 8)


@pytest.mark.parametrize("seed", range(4))
def test_operations_equal_rebuilding(spark, seed):
    r = random.Random(seed)
    b = r.choice([1, 2, 4, 8])
    some = lambda n: {(r.randrange(4), r.randrange(50)) for _ in range(n)}
    a, c = some(90), some(25)
    built = sets.build(frame(spark, a), b)
    assert as_dict(sets.union(built, frame(spark, c), b)) == chunks_of(a | c, b)
    assert as_dict(sets.difference(built, frame(spark, c), b)) == chunks_of(a - c, b)
    assert as_dict(sets.intersect(built, sets.build(frame(spark, c), b))) == chunks_of(a & c, b)
    for k in (0, 17, 33, 49):
        low, found, high = sets.split(built, k)
        assert as_dict(low) == chunks_of({x for x in a if x[1] < k}, b)
        assert as_dict(high) == chunks_of({x for x in a if x[1] > k}, b)
        assert {x["owner"] for x in found.collect()} == {o for o, e in a if e == k}


def test_head_deletion_chain(spark):
    """Two heads in a row go: their tails fall to the head before; the first head goes: its tail falls to the prefix."""
    b = 4
    h = heads_below(80, b)
    a = {(1, x) for x in range(80)}
    built = sets.build(frame(spark, a), b)
    for gone in ({h[1], h[2]}, {h[0]}, set(h), {999}, set(range(80))):
        d = {(1, x) for x in gone}
        assert as_dict(sets.difference(built, frame(spark, d), b)) == chunks_of(a - d, b)


def test_values_are_folded(spark):
    rows = [(1, x % 7, float(x)) for x in range(30)]
    df = spark.createDataFrame(rows, SCHEMA + ", val double")
    for how, f in (("sum", sum), ("min", min), ("max", max)):
        got = {r["elem"]: r["val"] for r in sets.entries(sets.build(df, 2, combine=how)).collect()}
        assert got == {e: f(v for _, x, v in rows if x == e) for e in range(7)}
    new = spark.createDataFrame([(1, 3, -1.0), (1, 50, 5.0)], SCHEMA + ", val double")
    got = {r["elem"]: r["val"] for r in sets.entries(sets.union(sets.build(df, 2, combine="sum"), new, 2)).collect()}
    assert got[3] == -1.0 and got[50] == 5.0 and got[1] == sum(v for _, x, v in rows if x == 1)


def test_inputs_stay_valid(spark):
    a = {(1, x) for x in range(40)}
    built = sets.build(frame(spark, a), 4)
    before = as_dict(built)
    sets.union(built, frame(spark, {(1, 100)}), 4).count()
    sets.difference(built, frame(spark, {(1, 5)}), 4).count()
    assert as_dict(built) == before


def test_range_aggregate(spark):
    rows = [(o, x, float(x * o)) for o in (1, 2) for x in range(60)]
    c = sets.build(spark.createDataFrame(rows, SCHEMA + ", val double"), 8)
    asked = spark.createDataFrame([(1, 10, 30), (2, 0, 59), (2, 58, 90)], "owner long, lo_bound long, hi_bound long")
    got = {(r["owner"], r["lo_bound"]): r["total"] for r in sets.range_agg(c, asked).collect()}
    assert got == {(1, 10): float(sum(range(10, 31))), (2, 0): float(2 * sum(range(60))), (2, 58): 2.0 * (58 + 59)}


def test_chunks_stay_within_their_bound(spark):
    import math

    n, b = 100_000, 16
    c = sets.build(spark.range(n).select(F.lit(1).cast("long").alias("owner"), F.col("id").alias("elem")), b, span=4096)
    stats = sets.chunk_stats(c).first()
    assert 0.9 < stats["heads"] * b / n < 1.1 and stats["largest"] < b * math.log(n) * 1.5 and stats["elements"] == n


def test_folds_of_a_set_and_a_batch(spark):
    old = spark.createDataFrame([(1, 2, 3.0), (1, 3, 4.0)], SCHEMA + ", val double")
    batch = spark.createDataFrame([(1, 2, 9.0, 1), (1, 2, 5.0, 2)], SCHEMA + ", val double, seq int")
    value = lambda c: {r["elem"]: r["val"] for r in sets.entries(c).collect()}
    assert value(sets.multi_insert(sets.build(old, 2), batch, 2, order="seq")) == {2: 5.0, 3: 4.0}
    assert value(sets.multi_insert(sets.build(old, 2, combine="count"), batch, 2, combine="count")) == {2: 3, 3: 1}
    assert value(sets.intersect(sets.build(old, 2), sets.build(batch.drop("seq"), 2, combine="max"), "sum")) == {2: 12.0}
    assert value(sets.intersect(sets.build(old, 2), sets.build(frame(spark, {(1, 3)}), 2))) == {3: 4.0}


def test_concatenation_checks_its_order(spark):
    low, high = sets.build(frame(spark, {(1, 1), (1, 5)}), 2), sets.build(frame(spark, {(1, 9)}), 2)
    assert as_dict(sets.concat_sets(low, frame(spark, {(1, 7)}), high, 2)) == chunks_of({(1, 1), (1, 5), (1, 7), (1, 9)}, 2)
    for middle in ({(1, 4)}, {(1, 9)}, {(1, 12)}):
        with pytest.raises(ValueError):
            sets.concat_sets(low, frame(spark, middle), high, 2)


def test_ranks_open_one_chunk_a_probe(spark):
    a = {(o, x * 3) for o in (1, 2) for x in range(40)}
    asked = spark.createDataFrame([(o, e) for o in (1, 2) for e in (-1, 0, 1, 17, 60, 117, 500)], "owner long, e long")
    got = {(r["owner"], r["e"]): r["rank"] for r in sets.rank(sets.build(frame(spark, a), 4, codec="bytecode"), asked).collect()}
    assert got == {(o, e): sum(x == o and y < e for x, y in a) for o, e in got} and len(got) == 14
