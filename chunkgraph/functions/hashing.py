"""The hash that decides chunk borders: the same function of an element in Spark, in SQL and in Python."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The modulus (every product stays below 2^62, so ANSI arithmetic never overflows) and the two steps.
MODULUS = 2147483647
STEP_ONE = (1103515245, 12345)
STEP_TWO = (1664525, 1013904223)


def mix_int(x: int) -> int:
    a = (x % MODULUS * STEP_ONE[0] + STEP_ONE[1]) % MODULUS
    return ((a ^ (a >> 15)) % MODULUS * STEP_TWO[0] + STEP_TWO[1]) % MODULUS


def mix_array(x: np.ndarray) -> np.ndarray:
    a = (x.astype(np.int64) % MODULUS * STEP_ONE[0] + STEP_ONE[1]) % MODULUS
    return ((a ^ (a >> 15)) % MODULUS * STEP_TWO[0] + STEP_TWO[1]) % MODULUS


def portable_hash_array(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """Of an array of non-negative integers."""
    return mix_array(mix_array(x) ^ mix_int(seed)) if seed else mix_array(x)


def mix(x: Column) -> Column:
    a = (x % MODULUS * STEP_ONE[0] + STEP_ONE[1]) % MODULUS
    return (a.bitwiseXOR(F.shiftright(a, 15)) % MODULUS * STEP_TWO[0] + STEP_TWO[1]) % MODULUS


def mix_sql(x: str) -> str:
    a = f"((({x}) % {MODULUS} * {STEP_ONE[0]} + {STEP_ONE[1]}) % {MODULUS})"
    return f"((xor({a}, {a} >> 15) % {MODULUS} * {STEP_TWO[0]} + {STEP_TWO[1]}) % {MODULUS})"


def portable_hash(x: Column, seed: int = 0) -> Column:
    """A member of the hash family; seeds other than 0 are mixed in after a first mix, so that they differ throughout."""
    return mix(mix(x).bitwiseXOR(F.lit(mix_int(seed)).cast("long"))) if seed else mix(x)


def portable_hash_int(x: int, seed: int = 0) -> int:
    return mix_int(mix_int(x) ^ mix_int(seed)) if seed else mix_int(x)


def portable_hash_sql(x: str, seed: int = 0) -> str:
    return mix_sql(f"xor({mix_sql(x)}, {mix_int(seed)})") if seed else mix_sql(x)


def wide_hash(x: Column, seed: int = 0) -> Column:
    """For ids of 2^31 and more: both halves count. Negative ids are taken modulo the modulus."""
    low, high = F.pmod(x, F.lit(MODULUS)), F.pmod(F.floor(x / F.lit(MODULUS)).cast("long"), F.lit(MODULUS))
    return portable_hash(low.bitwiseXOR(mix(high)), seed)


def is_head(x: Column, b: int, seed: int = 0) -> Column:
    """Does a chunk begin at this element? True for one of b elements, whatever set they are in."""
    return portable_hash(x, seed) % b == 0


def is_head_sql(x: str, b: int, seed: int = 0) -> str:
    return f"({portable_hash_sql(x, seed)} % {b} = 0)"
