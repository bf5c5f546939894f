"""Readers of the given tables and the store for sketches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """Keys from Parquet, ORC, CSV or JSON."""
    return spark.read.format(kind).options(**options).load(path)


def words_to_binary(sketches: DataFrame) -> DataFrame:
    """Words as little-endian bytes, for storage."""
    @pandas_udf("binary")
    def pack(words: pd.Series) -> pd.Series:
        return words.map(lambda w: np.asarray(w, "<i8").tobytes())

    return sketches.withColumn("words", pack("words"))


def binary_to_words(sketches: DataFrame) -> DataFrame:
    @pandas_udf("array<long>")
    def unpack(words: pd.Series) -> pd.Series:
        return words.map(lambda w: np.frombuffer(w, "<i8"))

    return sketches.withColumn("words", unpack("words"))


def write_sketches(sketches: DataFrame, path: str, partition_by: tuple[str, ...] = (), mode: str = "append") -> None:
    writer = words_to_binary(sketches).write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def read_sketches(spark: SparkSession, path: str) -> DataFrame:
    return binary_to_words(spark.read.parquet(path))


def compatible(a: DataFrame, b: DataFrame) -> DataFrame:
    """Both sketch tables together; a row of another format, hash or size raises."""
    both = a.unionByName(b)
    kinds = both.select("format", "hash_id", "registers").distinct().groupBy().agg(F.count(F.lit(1)).alias("kinds"))
    checked = both.crossJoin(F.broadcast(kinds))  # one row
    return checked.where(F.when(F.col("kinds") > 1, F.raise_error(F.lit("sketches of different formats can't be merged"))).otherwise(True)).drop("kinds")
