"""Stored sketches, aggregates of SQL text, ranks beyond a word, and late rows of a stream."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from densecount import sources
from densecount.functions import hashing
from densecount.operators import build
from densecount.streaming import sqlapi, windows


def keys(spark, n=30_000):
    return spark.range(n).select((F.col("id") % 3).cast("int").alias("g"), F.col("id").alias("k"))


def test_store_round_trip(spark, tmp_path):
    made = build.sketch(keys(spark), "k", ["g"])
    sources.write_sketches(made, str(tmp_path / "s"), ("g",))
    back = sources.read_sketches(spark, str(tmp_path / "s"))
    assert {r["g"]: list(r["words"]) for r in back.collect()} == {r["g"]: list(r["words"]) for r in made.collect()}
    assert sources.compatible(made, back.select(*made.columns)).count() == 6
    with pytest.raises(Exception, match="different formats"):
        sources.compatible(made, build.sketch(keys(spark), "k", ["g"], 512)).collect()


def test_hash_twins(spark):
    k = np.array([0, 1, -1, 7, 2**62, -(2**63), 12345678901], np.int64)
    rows = build.hashed(spark.createDataFrame([(int(x),) for x in k], "k long"), "k", ["k"], 11).collect()
    h = hashing.mix64_np(k)
    assert {r["k"]: (r["h"] % 2**64, r["z"]) for r in rows} == {int(a): (int(b), int(z)) for a, b, z in zip(k, h, hashing.rank_np(h), strict=True)}


def test_aggregates_make_the_same_sketch(spark):
    sqlapi.register(spark)
    df = keys(spark).unionByName(spark.sql("SELECT 0 AS g, CAST(NULL AS LONG) AS k"))
    got = {r["g"]: list(r["s"]) for r in df.groupBy("g").agg(sqlapi.dc_sketch_agg("k").alias("s")).collect()}
    want = {r["g"]: [r["registers"], r["floor"], *r["words"]] for r in build.sketch(df, "k", ["g"]).collect()}
    assert got == want
    one = df.groupBy("g").agg(sqlapi.dc_sketch_agg("k").alias("s")).agg(sqlapi.dc_merge_agg("s").alias("s")).select(sqlapi.dc_size("s").alias("n")).first()["n"]
    assert abs(one / 30_000 - 1) < 0.06
    none = spark.sql("SELECT CAST(NULL AS LONG) AS k").agg(sqlapi.dc_sketch_agg("k").alias("s")).select(sqlapi.dc_size("s").alias("n")).first()["n"]
    assert none == 0


def test_wide_levels_cross_the_word(spark):
    rows = spark.createDataFrame([(0, 63), (0, 62), (0, 61), (1, 64), (1, 62), (2, 5), (2, 4), (3, 125), (3, 200), (4, 0)], "bucket int, z int")
    got = {r["bucket"]: (r["zmax"], r["hist"]) for r in build.wide_levels(build.wide_bitmaps(rows)).collect()}
    assert got == {0: (63, 3), 1: (64, 1), 2: (5, 2), 3: (125, 0), 4: (0, 0)}


def test_late_rows_are_dropped_and_repeats_change_nothing(spark, tmp_path):
    where = str(tmp_path / "in")
    # Spark drops rows by the watermark of the batch before, so the late one comes in the third
    parts = [[(1, "2024-01-01 10:00:00"), (2, "2024-01-10 10:00:00")], [(2, "2024-01-10 10:00:00")], [(3, "2024-01-01 11:00:00"), (4, "2024-01-20 00:00:00")]]
    for part in parts:
        spark.createDataFrame(part, "user long, at string").select("user", F.to_timestamp("at").alias("ts")).coalesce(1).write.mode("append").parquet(where)
    stream = spark.readStream.schema("user long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(where)
    out = windows.run_available(windows.windowed_bitmaps(stream, "user", "1 day", 11), "append")
    got = {(r["day"], r["bucket"]): r["bitmap"] for r in out.select(F.date_format("window.start", "dd").alias("day"), "bucket", "bitmap").collect()}
    want = build.hashed(spark.createDataFrame([("01", 1), ("10", 2)], "day string, k long"), "k", ["day"], 11).collect()
    assert got == {(r["day"], r["bucket"]): 1 << r["z"] for r in want}


def test_appended_rows_are_files_not_driver_memory(spark, tmp_path):
    where = str(tmp_path / "in")
    at = [(1, "2024-01-01 10:00:00"), (1, "2024-01-01 10:20:00"), (1, "2024-01-01 12:00:00"), (2, "2024-01-02 00:00:00")]
    spark.createDataFrame(at, "user_id long, at string").select("user_id", F.to_timestamp("at").alias("ts")).coalesce(1).write.parquet(where)
    stream = spark.readStream.schema("user_id long, ts timestamp").parquet(where)
    out = windows.run_available(windows.session_counts(stream), "append")
    assert sorted((r["user_id"], r["n"]) for r in out.collect()) == [(1, 1), (1, 2)]
    assert out.inputFiles()
    spark.createDataFrame([], "user_id long, ts timestamp").write.parquet(str(tmp_path / "none"))
    none = windows.run_available(windows.session_counts(spark.readStream.schema("user_id long, ts timestamp").parquet(str(tmp_path / "none"))), "append")
    assert none.count() == 0
