"""Relational sketch building: a level bitmap per register, floors, states, histograms.

A register's state is a projection of the OR of its levels, so partial and final
``bit_or`` aggregates give the sketch exactly, in any order and however often an element is
repeated. The shuffle key is (group, register): a hot group spreads over its registers.
"""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from ..functions import codec, hashing


def hashed(df: DataFrame, key: str | Column, by: Sequence[str] = (), registers: int | Column = 1408, seed: int | Column = 0, kind: str | None = None) -> DataFrame:
    """by..., h, bucket, z of every non-null key. ``kind`` follows the key's type if not given."""
    kind = kind or hashing.kind_of(df.select(key).schema[0].dataType)
    extra = [seed.alias("_seed")] if isinstance(seed, Column) else []
    rows = df.select(*by, hashing.key64(key, kind=kind).alias("_key"), *extra).where("_key is not null")
    rows = hashing.mix64(rows, "_key", "h", F.col("_seed") if extra else seed)
    ranked = hashing.with_rank(rows.withColumn("bucket", hashing.bucket(F.col("h"), registers)))
    return ranked.select(*by, "h", "bucket", (F.col("z") + hashing.barrier("int")).alias("z"))


def register_bitmaps(df: DataFrame, key: str | Column, by: Sequence[str] = (), registers: int | Column = 1408, seed: int | Column = 0, kind: str | None = None) -> DataFrame:
    """by..., bucket, bitmap: bit z is set when rank z was seen in the register."""
    rows = hashed(df, key, by, registers, seed, kind)
    return rows.groupBy(*by, "bucket").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("z"))).alias("bitmap"))


def with_levels(bitmaps: DataFrame) -> DataFrame:
    """Add zmax and hist (2 * [zmax-1 seen] + [zmax-2 seen])."""
    top = hashing.with_rank(bitmaps, "bitmap", "_clz", 64).withColumn("zmax", F.lit(63) - F.col("_clz")).drop("_clz")
    z = F.col("zmax")
    return top.withColumn("hist", codec.bit_at(F.col("bitmap"), z - 1) * 2 + codec.bit_at(F.col("bitmap"), z - 2))


def state_histogram(bitmaps: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """by..., z, hist, n of the filled registers: all that the estimators need."""
    rows = with_levels(bitmaps).groupBy(*by, F.col("zmax").alias("z"), "hist")
    return rows.agg(F.count(F.lit(1)).alias("n"))


# --- ranks of more than one hash word -----------------------------------------------------

#: levels in the lower of two longs; the sign bit of each stays free
WIDE = 63
#: the rank to which the lowest register is brought before estimating
LOWERED = 24


def wide_hashed(df: DataFrame, key: str, by: Sequence[str] = (), registers: int = 1408) -> DataFrame:
    """by..., bucket, z with ranks up to 127 from two further hashes of an integer key."""
    rows = hashing.mix64(df.select(*by, F.col(key).cast("long").alias("_key")).where("_key is not null"), "_key", "h")
    ranked = hashing.wide_rank(rows.withColumn("bucket", hashing.bucket(F.col("h"), registers)), "_key")
    return ranked.select(*by, "bucket", (F.col("z") + hashing.barrier("int")).alias("z"))


def wide_bitmaps(rows: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """by..., bucket, low, high of rows (by..., bucket, z): bitmaps of levels 0 to 62 and 63 to
    125 (higher ones count as 125). A register is two longs whatever the cardinality."""
    z, none = F.least(F.col("z"), F.lit(2 * WIDE - 1)), F.lit(0).cast("long")
    bit = lambda at: F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(at, F.lit(0)))
    low, high = F.when(z < WIDE, bit(z)).otherwise(none), F.when(z >= WIDE, bit(z - WIDE)).otherwise(none)
    return rows.groupBy(*by, "bucket").agg(F.bit_or(low).alias("low"), F.bit_or(high).alias("high"))


def wide_levels(bitmaps: DataFrame) -> DataFrame:
    """Add zmax and hist, as ``with_levels`` does for one long."""
    top = hashing.with_rank(hashing.with_rank(bitmaps, "low", "_cl", 64), "high", "_ch", 64)
    top = top.withColumn("zmax", F.when(F.col("high") != 0, F.lit(63 + WIDE) - F.col("_ch")).otherwise(F.lit(63) - F.col("_cl"))).drop("_cl", "_ch")

    def seen(z: Column) -> Column:
        return F.when(z >= WIDE, codec.bit_at(F.col("high"), z - WIDE)).otherwise(codec.bit_at(F.col("low"), z))

    return top.withColumn("hist", seen(F.col("zmax") - 1) * 2 + seen(F.col("zmax") - 2))


def lowered(levels: DataFrame, registers: int) -> DataFrame:
    """Add shift and z = zmax - shift (columns g, zmax): once every register is filled, a
    sketch that stands ``shift`` ranks lower estimates 2**shift times less, so ranks of any
    height reach the estimators within one word."""
    low = levels.groupBy("g").agg(F.when(F.count(F.lit(1)) < registers, 0).otherwise(F.greatest(F.lit(0), F.min("zmax") - LOWERED)).alias("shift"))
    return levels.join(low, "g").withColumn("z", F.least(F.lit(62), F.col("zmax") - F.col("shift")))


def floor_of(filled: Column, low: Column, registers: int) -> Column:
    """Shared floor: two below the lowest register once all are filled, else -1."""
    return F.when(filled < registers, -1).otherwise(F.greatest(F.lit(-1), low - codec.MARGIN)).cast("int")


def floors(bitmaps: DataFrame, by: Sequence[str] = (), registers: int = 1408) -> DataFrame:
    levels = with_levels(bitmaps)
    grouped = levels.groupBy(*by) if by else levels.groupBy()
    return grouped.agg(F.count(F.lit(1)).alias("filled"), F.min("zmax").alias("low")).select(*by, floor_of(F.col("filled"), F.col("low"), registers).alias("floor"))


def register_states(bitmaps: DataFrame, by: Sequence[str] = (), registers: int = 1408) -> DataFrame:
    """by..., bucket, floor, state of the filled registers."""
    f = floors(bitmaps, by, registers)
    joined = with_levels(bitmaps).join(f, list(by)) if by else with_levels(bitmaps).crossJoin(F.broadcast(f))  # one row
    return joined.select(*by, "bucket", "floor", codec.state_from_bitmap(F.col("bitmap"), F.col("zmax"), F.col("floor")).alias("state"))


def packed_words(states: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """by..., word, digits: the 64-bit words of a sketch as decimal numbers (words with no
    filled register are 0 and left out)."""
    word = F.floor(F.col("bucket") / codec.DIGITS).cast("int").alias("word")
    power = F.lit(None).cast("decimal(20,0)")
    for i in range(codec.DIGITS):
        power = F.when(F.col("bucket") % codec.DIGITS == i, F.lit(str(codec.RADIX**i)).cast("decimal(20,0)")).otherwise(power)
    digit = (F.col("state").cast("decimal(2,0)") * power).cast("decimal(22,0)")
    return states.groupBy(*by, word).agg(F.sum(digit).alias("digits"))


def sketch(df: DataFrame, key: str | Column, by: Sequence[str] = (), memory_bytes: int = 1024, kind: str | None = None, mode: str = "relational") -> DataFrame:
    """A row per group: format, hash_id, registers, floor, words (array of longs).

    ``mode`` relational is idempotent and order-free; sequential drops history above tier 13
    as it goes, as a single-pass builder does, and merges the tasks' sketches."""
    registers = codec.registers_for(memory_bytes)
    if mode == "sequential":
        from . import sequential

        merged = sequential.merge_sketches(sequential.sketch_partitions(df, key, by, registers), by)
        return merged.select(*by, F.lit(1).alias("format"), F.lit(hashing.HASH_ID).alias("hash_id"), F.lit(registers).alias("registers"), "floor", "words")
    if mode != "relational":
        raise ValueError(f"unknown mode {mode}")
    states = register_states(register_bitmaps(df, key, by, registers, kind=kind), by, registers)
    words = packed_words(states, by).select(*by, "word", _signed(F.col("digits")).alias("value"))
    grouped = words.groupBy(*by) if by else words.groupBy()
    filled = F.map_from_entries(F.collect_list(F.struct("word", "value")))  # at most a sketch's words
    every = F.transform(F.sequence(F.lit(0), F.lit(codec.words_for(registers) - 1)), lambda i: F.coalesce(F.try_element_at(F.col("filled"), i), F.lit(0).cast("long")))
    low = states.groupBy(*by).agg(F.first("floor").alias("floor")) if by else states.groupBy().agg(F.first("floor").alias("floor"))
    rows = grouped.agg(filled.alias("filled"))
    rows = rows.join(low, list(by)) if by else rows.crossJoin(F.broadcast(low))  # one row
    return rows.select(*by, F.lit(1).alias("format"), F.lit(hashing.HASH_ID).alias("hash_id"), F.lit(registers).alias("registers"), "floor", every.alias("words"))


def _signed(digits: Column) -> Column:
    """An unsigned 64-bit decimal as the long with the same bits."""
    high = digits >= F.lit(str(1 << 63)).cast("decimal(22,0)")
    return F.when(high, digits - F.lit(str(1 << 64)).cast("decimal(22,0)")).otherwise(digits).cast("long")


def registers_of(sketches: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """by..., bucket, z, hist of the filled registers of packed sketches."""
    import numpy as np

    @pandas_udf("array<int>")
    def unpack(words: pd.Series, registers: pd.Series) -> pd.Series:
        return pd.Series([codec.unpack(np.asarray(w), int(b)).astype("int32") for w, b in zip(words, registers, strict=True)])

    rows = sketches.select(*by, "floor", F.posexplode(unpack("words", "registers")).alias("bucket", "state")).where("state > 0")
    return rows.select(*by, "bucket", (codec.exponent_of(F.col("state")) + F.col("floor")).alias("z"), codec.history_of(F.col("state")).alias("hist"), "state", "floor")


def early_exit(df: DataFrame, key: str, by: Sequence[str], floors_: DataFrame, registers: int, seed: int = 0) -> DataFrame:
    """Drop rows that can't change a sketch: rank below its floor. ``floors_`` (by..., floor)
    may come from any subset of the data: floors only rise."""
    rows = hashed(df, key, by, registers, seed)
    joined = rows.join(floors_, list(by), "left") if by else rows.crossJoin(F.broadcast(floors_))  # one row
    return joined.where(F.col("z") >= F.coalesce("floor", F.lit(-1))).drop("floor")


def merge_bitmaps(parts: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """Union of sketches held as bitmaps: associative, commutative, idempotent."""
    return parts.groupBy(*by, "bucket").agg(F.bit_or("bitmap").alias("bitmap"))


def rollup(bitmaps: DataFrame, dims: Sequence[str], sets: Sequence[Sequence[str]]) -> DataFrame:
    """Coarser sketches from the finest ones: for each set of dimensions kept, the others
    null, with ``level`` the set's number. The data are scanned once."""
    out = None
    for i, kept in enumerate(sets):
        part = bitmaps.groupBy(*kept, "bucket").agg(F.bit_or("bitmap").alias("bitmap"))
        part = part.select(F.lit(i).alias("level"), *[F.col(d) if d in kept else F.lit(None).cast(bitmaps.schema[d].dataType).alias(d) for d in dims], "bucket", "bitmap")
        out = part if out is None else out.unionByName(part)
    return out


def numbered(df: DataFrame, coarse: Column, *order: str, out: str = "rn") -> DataFrame:
    """Add ``out``: each row's place from 1 in the order of ``order``, of which ``coarse`` is a
    monotone function with far fewer values. Only counts per coarse value meet in one task."""
    parts = df.withColumn("_part", coarse)
    before = W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    offsets = parts.groupBy("_part").agg(F.count(F.lit(1)).alias("_n")).select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_from"))
    ranked = parts.withColumn("_r", F.row_number().over(W.partitionBy("_part").orderBy(*order)))
    return ranked.join(offsets, "_part").withColumn(out, F.col("_r") + F.col("_from")).drop("_part", "_r", "_from")


def running_bitmaps(bitmaps: DataFrame, step: str, marks: DataFrame) -> DataFrame:
    """(step, bucket, bitmap) of everything up to each of the ``marks`` (column ``step``) from
    bitmaps per step: cumulative ORs, so no element is looked at twice."""
    every = bitmaps.select("bucket").distinct().crossJoin(F.broadcast(marks))  # a few marks
    filled = every.join(bitmaps, [step, "bucket"], "left")
    upto = W.partitionBy("bucket").orderBy(step).rowsBetween(W.unboundedPreceding, W.currentRow)
    return filled.select(step, "bucket", F.bit_or(F.coalesce("bitmap", F.lit(0).cast("long"))).over(upto).alias("bitmap")).where("bitmap <> 0")
