import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from chunkgraph.functions.codec import byte_length, decode_bytes, delta_decode, delta_encode, encode_bytes, zigzag
from chunkgraph.functions.hashing import is_head, mix_int, portable_hash, portable_hash_int, wide_hash

EDGES = [0, 1, 127, 128, 16383, 16384, 2**21 - 1, 2**21, 2**31, 2**40]


def test_byte_code_lengths():
    assert [len(encode_bytes(np.array([x]))) for x in EDGES] == [1, 1, 1, 2, 2, 3, 3, 4, 5, 6]


@given(st.lists(st.integers(-(2**63), 2**63 - 1), max_size=60))
@settings(max_examples=200, deadline=None)
def test_byte_code_round_trip(values):
    assert decode_bytes(encode_bytes(np.array(values, np.int64))).tolist() == values


def test_column_functions(spark):
    df = spark.createDataFrame([(x,) for x in EDGES], "x long")
    rows = df.select("x", byte_length(F.col("x")).alias("n"), portable_hash(F.col("x")).alias("h"), portable_hash(F.col("x"), 9).alias("s"), wide_hash(-F.col("x")).alias("w"), zigzag(-F.col("x")).alias("z")).collect()
    for r in rows:
        assert r["n"] == len(encode_bytes(np.array([r["x"]])))
        assert r["h"] == portable_hash_int(r["x"]) == mix_int(r["x"]) and r["s"] == portable_hash_int(r["x"], 9)
        assert r["w"] >= 0 and r["z"] == max(0, 2 * r["x"] - 1)


def test_delta_round_trip(spark):
    lists = [[], [5], [0, 1, 2], [3, 100, 10_000_000_000]]
    df = spark.createDataFrame([(x,) for x in lists], "e array<bigint>")
    got = df.select("e", delta_encode(F.col("e")).alias("d"), delta_decode(delta_encode(F.col("e"))).alias("back")).collect()
    assert all(r["e"] == r["back"] for r in got) and got[3]["d"] == [3, 97, 9_999_999_900]


def test_head_share(spark):
    x = spark.range(200_000)
    for b in (2, 8, 16, 256):
        share = x.where(is_head(F.col("id"), b)).count() * b / 200_000
        assert 0.97 < share < 1.06
