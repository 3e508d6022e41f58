"""Three hash families: mix64 for the kernels, xxhash64 in SQL, pair31 alike in NumPy, Spark and DuckDB."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P31 = 2**31 - 1


def mix64(x: np.ndarray, seed: int, out: np.ndarray | None = None, spare: np.ndarray | None = None) -> np.ndarray:
    """A 64-bit finaliser over x xor a spread seed; into ``out``, by way of ``spare``, if they are given."""
    out = np.bitwise_xor(x, np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF), out=out)
    spare = np.empty_like(out) if spare is None else spare
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        np.bitwise_xor(out, np.right_shift(out, np.uint64(shift), out=spare), out=out)
        np.multiply(out, np.uint64(factor), out=out)
    return np.bitwise_xor(out, np.right_shift(out, np.uint64(31), out=spare), out=out)


def trailing_zeros(h: np.ndarray) -> np.ndarray:
    """Count of trailing zero bits; 64 for 0."""
    return np.bitwise_count((h & (~h + np.uint64(1))) - np.uint64(1)).astype(np.int64)


def trailing_zeros_sql(h: Column) -> Column:
    return F.bit_count(h.bitwiseAND(F.negative(h)) - 1)


def pair31_factors(index: int) -> tuple[int, int, int]:
    """The three factors of the hash with this index."""
    i = index + 1
    return (48271 * i * i + 11) % P31, (69621 * i * i * i + 7919) % P31, (16807 * i + 104729) % P31


def pair31(lo: np.ndarray, hi: np.ndarray, index: int) -> np.ndarray:
    a, b, c = pair31_factors(index)
    return ((a * lo) % P31 + (b * hi) % P31 + c) % P31


def pair31_sql(lo: Column, hi: Column, a: Column, b: Column, c: Column) -> Column:
    """No product passes 2**62, so ANSI arithmetic never overflows."""
    p = F.lit(P31).cast("long")
    return ((a * lo) % p + (b * hi) % p + c) % p
