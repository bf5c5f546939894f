"""64-bit element hashes as DataFrame stages.

Spark's ANSI arithmetic raises on overflow, so additions modulo 2**64 work on 32-bit halves.
Each step is a projection of its own: a single nested expression would repeat its operand
several times per step and grow exponentially, while projections stay linear and are
compiled into one loop. Longs are read as unsigned.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

HASH_ID = "mix64-v1"
_LOW = 0xFFFFFFFF
SEED_STEP = 0x9E3779B97F4A7C15


def signed(x: int) -> int:
    """The long with the bits of an unsigned 64-bit integer."""
    x &= (1 << 64) - 1
    return x - (1 << 64) if x >> 63 else x


def add64(a: Column, b: Column) -> Column:
    """a + b modulo 2**64."""
    low = a.bitwiseAND(_LOW) + b.bitwiseAND(_LOW)
    high = F.shiftrightunsigned(a, 32) + F.shiftrightunsigned(b, 32) + F.shiftrightunsigned(low, 32)
    return F.shiftleft(high, 32).bitwiseOR(low.bitwiseAND(_LOW))


def barrier(kind: str = "long") -> Column:
    """0, but not for the optimiser: filters (also those that joins imply) stay above it.
    Pushed through the stages below they would repeat their operands exponentially."""
    return F.when(F.spark_partition_id() < 0, 1).otherwise(0).cast(kind)


def _fold(c: Column, n: int) -> Column:
    return c.bitwiseXOR(F.shiftrightunsigned(c, n))


def mix64(df: DataFrame, key: str, out: str = "h", seed: int | Column = 0) -> DataFrame:
    """Add ``out``: the shift-add mix of the long column ``key``. A seed (constant, or a
    long column that already holds ``seed_word``) gives an independent instance."""
    k = F.col(key).cast("long")
    if isinstance(seed, Column):
        k = k.bitwiseXOR(seed)
    elif seed:
        k = k.bitwiseXOR(F.lit(signed(seed * SEED_STEP)))
    x = F.col(out)
    df = df.withColumn(out, k)
    df = df.withColumn(out, add64(F.bitwise_not(x), F.shiftleft(x, 21)))
    df = df.withColumn(out, _fold(x, 24))
    df = df.withColumn(out, add64(add64(x, F.shiftleft(x, 3)), F.shiftleft(x, 8)))
    df = df.withColumn(out, _fold(x, 14))
    df = df.withColumn(out, add64(add64(x, F.shiftleft(x, 2)), F.shiftleft(x, 4)))
    df = df.withColumn(out, _fold(x, 28))
    return df.withColumn(out, add64(x, F.shiftleft(x, 31)).bitwiseXOR(barrier()))


def seed_word(seed: Column) -> Column:
    """seed * odd constant modulo 2**64, for a small non-negative integer column."""
    s, hi, lo = seed.cast("long"), SEED_STEP >> 32, SEED_STEP & _LOW
    low = s * F.lit(lo)
    return F.shiftleft(s * F.lit(hi) + F.shiftrightunsigned(low, 32), 32).bitwiseOR(low.bitwiseAND(_LOW))


def key64(*cols: Column | str, kind: str = "long") -> Column:
    """A canonical long: the value itself for integers (``kind`` long), 60 bits of MD5 of the
    text form for anything else. In a composite every part carries its length, and a null
    part is a value of its own, so different tuples have different texts; a single null is
    null."""
    c = [F.col(x) if isinstance(x, str) else x for x in cols]
    if len(c) == 1 and kind == "long":
        return c[0].cast("long")
    parts = [x.cast("string") for x in c]
    text = F.concat(*[F.coalesce(F.concat(F.length(x).cast("string"), F.lit(":"), x), F.lit("~")) for x in parts]) if len(c) > 1 else parts[0]
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def kind_of(kind: T.DataType) -> str:
    """How keys of a column of this type become longs: integers as they are, all others
    (fractions too, which a cast would cut) by their text."""
    return "long" if isinstance(kind, T.IntegralType) else "text"


def fast64(*cols: Column | str) -> Column:
    """The engine's own 64-bit hash; as good, but with no twin in other engines."""
    return F.xxhash64(*cols)


def bucket(h: Column, registers: int | Column) -> Column:
    """Unsigned remainder of the hash: any number of registers."""
    b = F.lit(registers) if isinstance(registers, int) else registers
    half = F.pmod(F.shiftrightunsigned(h, 1), b)
    return F.pmod(half * 2 + h.bitwiseAND(1), b).cast("int")


def bucket_pow2(h: Column, p: int) -> Column:
    """The lowest p bits."""
    return h.bitwiseAND((1 << p) - 1).cast("int")


def with_rank(df: DataFrame, h: str = "h", out: str = "z", most: int = 62) -> DataFrame:
    """Add ``out``: leading zeros of the unsigned hash, by a ladder of halving tests."""
    x, n = "_rest", out
    df = df.withColumns({x: F.col(h), n: F.lit(0)})
    for step in (32, 16, 8, 4, 2, 1):
        empty = F.shiftrightunsigned(F.col(x), 64 - step) == 0
        df = df.withColumns({x: F.when(empty, F.shiftleft(F.col(x), step)).otherwise(F.col(x)), n: F.when(empty, F.col(n) + step).otherwise(F.col(n))})
    return df.withColumn(n, F.least(F.lit(most), F.col(n)).cast("int")).drop(x)


def wide_rank(df: DataFrame, key: str, out: str = "z") -> DataFrame:
    """Ranks up to 127 from two independent hashes."""
    df = with_rank(mix64(df, key, "_hi", 1), "_hi", "_zh", 64)
    df = with_rank(mix64(df, key, "_lo", 2), "_lo", "_zl", 63)
    return df.withColumn(out, F.when(F.col("_hi") == 0, F.col("_zl") + 64).otherwise(F.col("_zh"))).drop("_hi", "_lo", "_zh", "_zl")


def mix64_np(key: np.ndarray) -> np.ndarray:
    """``mix64`` of an array of longs, as unsigned words."""
    x = np.ascontiguousarray(key, np.int64).view(np.uint64)
    u = np.uint64
    x = ~x + (x << u(21))
    x = x ^ (x >> u(24))
    x = x + (x << u(3)) + (x << u(8))
    x = x ^ (x >> u(14))
    x = x + (x << u(2)) + (x << u(4))
    x = x ^ (x >> u(28))
    return x + (x << u(31))


def rank_np(h: np.ndarray, most: int = 62) -> np.ndarray:
    """Leading zeros of unsigned words, by the ladder of ``with_rank``."""
    x, n = h.copy(), np.zeros(len(h), np.int64)
    for step in (32, 16, 8, 4, 2, 1):
        empty = (x >> np.uint64(64 - step)) == 0
        x, n = np.where(empty, x << np.uint64(step), x), n + step * empty
    return np.minimum(n, most)
