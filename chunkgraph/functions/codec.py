"""Difference coding of chunks, and the byte code of the differences (seven data bits and a continue bit).

A chunk is coded as its first element and the differences behind it. Differences of ascending elements are positive; a
negative first element is coded as its 64-bit two's complement, in ten bytes. Chunk rows hold their tail as `elems`
(plain), `deltas` (differences) or `payload` (byte code); `opened` and `coded` go from one to the other, and both work
on whole Arrow batches, never value by value.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Code lengths grow at these values; one byte more from 2^63 on, where the top bit is set (negative numbers).
_LIMITS = [1 << (7 * k) for k in range(1, 9)]
#: Columns that hold a chunk's tail, by codec.
COLUMNS = {"plain": "elems", "delta": "deltas", "bytecode": "payload"}


def delta_encode(elems: Column) -> Column:
    """[first, differences...] of a sorted array."""
    shifted = F.concat(F.array(F.lit(0).cast("long")), F.slice(elems, 1, F.greatest(F.size(elems) - 1, F.lit(0))))
    return F.when(F.size(elems) == 0, elems).otherwise(F.zip_with(elems, shifted, lambda x, y: x - y))


def delta_decode(deltas: Column) -> Column:
    """The sorted array again, as running sums."""
    start = F.struct(F.array().cast("array<bigint>").alias("out"), F.lit(0).cast("long").alias("sum"))
    step = lambda a, d: F.struct(F.concat(a["out"], F.array(a["sum"] + d)).alias("out"), (a["sum"] + d).alias("sum"))
    return F.aggregate(deltas, start, step, lambda a: a["out"])


def zigzag(x: Column) -> Column:
    """Signed to unsigned, small magnitudes first; for values whose sign varies, such as differences of unordered ids."""
    return F.shiftleft(x, 1).bitwiseXOR(F.shiftright(x, 63))


def byte_length(x: Column) -> Column:
    """Bytes of the code of a number."""
    out = F.lit(len(_LIMITS) + 1)
    for k in reversed(range(len(_LIMITS))):
        out = F.when(x < _LIMITS[k], k + 1).otherwise(out)
    return F.when(x < 0, len(_LIMITS) + 2).otherwise(out)


def byte_length_sql(x: str) -> str:
    return f"CASE WHEN {x} < 0 THEN {len(_LIMITS) + 2} " + " ".join(f"WHEN {x} < {limit} THEN {k + 1}" for k, limit in enumerate(_LIMITS)) + f" ELSE {len(_LIMITS) + 1} END"


def encode_bytes(values: np.ndarray) -> bytes:
    """Byte code of an array of integers."""
    return _encoded(np.asarray(values, np.int64).view(np.uint64))[0].tobytes()


def _encoded(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The code of unsigned numbers, and how many bytes each takes."""
    size = np.ones(len(values), np.int64)
    for limit in [*_LIMITS, 1 << 63]:
        size += values >= np.uint64(limit)
    start = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), np.uint8)
    for k in range(int(size.max(initial=0))):
        has = size > k
        out[start[has] + k] = ((values[has] >> np.uint64(7 * k)) & np.uint64(127)) | np.where(size[has] > k + 1, 128, 0).astype(np.uint64)
    return out, size


def decode_bytes(code: bytes) -> np.ndarray:
    return _decoded(np.frombuffer(code, np.uint8))[0]


def _decoded(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The numbers, and where the code of each ends."""
    ends = np.flatnonzero(raw < 128)
    starts = np.concatenate(([0], ends[:-1] + 1)).astype(np.int64)
    out = np.zeros(len(ends), np.uint64)
    size = ends - starts + 1
    for k in range(int(size.max(initial=0))):
        has = size > k
        out[has] |= (raw[starts[has] + k] & np.uint8(127)).astype(np.uint64) << np.uint64(7 * k)
    return out.view(np.int64), ends + 1


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(values, sizes) of a list column; null is an empty list."""
    sizes = np.asarray(pc.fill_null(pc.list_value_length(column), 0)).astype(np.int64)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64), sizes


def _as_lists(values: np.ndarray, sizes: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(values, pa.int64()))


def _steps(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Differences, anew in each list."""
    out, first = np.diff(values, prepend=0), (np.cumsum(sizes) - sizes)[sizes > 0]
    out[first] = values[first]
    return out


def _sums(steps: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Running sums, anew in each list."""
    total, some = np.cumsum(steps), sizes[sizes > 0]
    first = np.cumsum(some) - some
    return total - np.repeat((total - steps)[first], some)


def encode_lists(column: pa.Array) -> pa.Array:
    """A column of sorted lists -> a column of byte codes of their differences."""
    values, sizes = _lists(column)
    code, width = _encoded(_steps(values, sizes).view(np.uint64))
    ends = np.concatenate(([0], np.cumsum(width)))[np.concatenate(([0], np.cumsum(sizes)))]
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(code)])


def decode_lists(column: pa.Array) -> pa.Array:
    """A column of byte codes -> a column of sorted lists."""
    column = pc.fill_null(column.cast(pa.binary()), b"")
    bytes_in = np.asarray(pc.binary_length(column)).astype(np.int64)
    raw = np.frombuffer(b"".join(column.to_pylist()), np.uint8)
    values, ends = _decoded(raw)
    sizes = np.diff(np.searchsorted(ends, np.concatenate(([0], np.cumsum(bytes_in))), side="right"))
    return _as_lists(_sums(values, sizes), sizes)


def _mapped(df: DataFrame, old: str, new: str, kind: str, f) -> DataFrame:
    """df with the column `old` replaced by `new`, f applied to whole Arrow columns."""
    kept = [c for c in df.columns if c != old]
    schema = ", ".join([*(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in kept), f"{new} {kind}"])

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), f(batch.column(old))], [*kept, new])

    return df.mapInArrow(run, schema)


def codec_of(chunks: DataFrame) -> str:
    return next(k for k, c in COLUMNS.items() if c in chunks.columns)


def opened(chunks: DataFrame) -> DataFrame:
    """Chunk rows of any codec with their tails as `elems`. Do it after rows were chosen: what is not touched stays coded."""
    how = codec_of(chunks)
    if how == "plain":
        return chunks
    if how == "delta":
        return _mapped(chunks, "deltas", "elems", "array<bigint>", lambda c: _as_lists(_sums(*(x := _lists(c))), x[1]))
    return _mapped(chunks, "payload", "elems", "array<bigint>", decode_lists)


def coded(chunks: DataFrame, how: str) -> DataFrame:
    """Chunk rows with `elems` in a codec: plain, delta or bytecode."""
    if how == "plain":
        return chunks
    if how == "delta":
        return chunks.withColumn("deltas", delta_encode(F.col("elems"))).drop("elems")
    return _mapped(chunks, "elems", "payload", "binary", encode_lists)


def encode_chunks(chunks: DataFrame) -> DataFrame:
    """chunks with `elems` replaced by `payload` (byte code of the differences) and `nbytes`."""
    return coded(chunks, "bytecode").withColumn("nbytes", F.octet_length("payload"))


def decode_chunks(rows: DataFrame) -> DataFrame:
    return opened(rows.drop("nbytes"))
