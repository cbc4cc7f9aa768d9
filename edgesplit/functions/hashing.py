"""Portable hash: the same integer in Spark, DuckDB and NumPy, so every hash-based method has a SQL twin."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# The modulus 2^31 - 1 and two multipliers of classic multiplicative generators.
MODULUS, FIRST, SECOND = 2_147_483_647, 48_271, 69_621
_SHIFT = 1_013_904_223


def portable(v: Column, seed: int = 0) -> Column:
    """Hash of a vertex id below the modulus; reduced before it is multiplied, so it never overflows."""
    once = F.pmod(F.pmod(v + F.lit(seed), F.lit(MODULUS)) * F.lit(FIRST), F.lit(MODULUS))
    high = F.shiftright(once, 9)
    return F.pmod((once.bitwiseXOR(high) + F.lit(_SHIFT)) * F.lit(SECOND), F.lit(MODULUS))


def portable_sql(v: str, seed: int = 0) -> str:
    """The same hash as DuckDB SQL."""
    once = f"(((({v}) + {seed}) % {MODULUS}) * {FIRST} % {MODULUS})"
    return f"((xor({once}, {once} >> 9) + {_SHIFT}) * {SECOND} % {MODULUS})"


def portable_numpy(v: np.ndarray, seed: int = 0) -> np.ndarray:
    once = (np.asarray(v, np.int64) + seed) % MODULUS * FIRST % MODULUS
    return ((once ^ (once >> 9)) + _SHIFT) * SECOND % MODULUS


def partition_of(v: Column, k: int, seed: int = 0) -> Column:
    return (portable(v, seed) % k).cast("int")


def string_id(text: Column) -> Column:
    """56 bits of MD5 as a non-negative long."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 14), 16, 10).cast("long")
