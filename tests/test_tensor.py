"""Kernels, encodings and measures against closed forms, fixed examples and each other."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from densecount import experiments, methods, metrics, sources
from densecount.functions import hashing
from densecount.operators import build, estimators, sequential, tensor
from densecount.plans import estimate


def test_kernel_agrees_with_the_sql_plan(spark):
    hist = build.state_histogram(build.register_bitmaps(spark.range(40_000).select(F.pmod("id", F.lit(7)).alias("g"), "id"), "id", ["g"], 352), ["g"])
    a = {r["g"]: r for r in estimators.all_components(hist, 352).collect()}
    b = {r["g"]: r for r in spark.sql(estimate.text("{hist}", 352), hist=hist).collect()}
    for g in b:
        for c in estimate.COMPONENTS:
            assert a[g][c] == pytest.approx(b[g][c], rel=1e-9), c


def test_keys_of_different_tuples_differ(spark):
    rows = spark.createDataFrame([(None, "a"), ("a", None), ("a|b", "c"), ("a", "b|c"), ("", "a"), ("1:a", "b")], "a string, b string")
    assert rows.select(hashing.key64("a", "b").alias("k")).distinct().count() == 6
    fractions = spark.createDataFrame([(1.2,), (1.9,), (None,)], "x double")
    assert build.hashed(fractions, "x").select("h").distinct().count() == 2


def test_numbered_is_row_number(spark):
    rows = spark.range(500).select(F.pmod(F.col("id") * 7919, F.lit(503)).alias("x")).repartition(5)
    got = [(r["x"], r["rn"]) for r in build.numbered(rows, F.floor(F.col("x") / 50), "x").collect()]
    assert sorted(got) == [(x, i + 1) for i, x in enumerate(sorted(x for x, _ in got))]


def test_modes_agree(spark):
    rows = spark.range(20_000).select(F.pmod("id", F.lit(2)).alias("g"), "id")
    a, b = ({r["g"]: r for r in build.sketch(rows, "id", ["g"], 256, mode=m).collect()} for m in ("relational", "sequential"))
    assert set(a) == set(b) and all(a[g]["registers"] == 352 and len(a[g]["words"]) == 32 for g in a)
    same = sum(x == y for g in a for x, y in zip(a[g]["words"], b[g]["words"], strict=True))
    assert same >= 60 and all(a[g]["floor"] == b[g]["floor"] for g in a)
    with pytest.raises(ValueError):
        build.sketch(rows, "id", mode="other")


def test_sketch_store_round_trip(spark, tmp_path):
    sketches = build.sketch(spark.range(9_000).select(F.pmod("id", F.lit(3)).alias("g"), "id"), "id", ["g"], 256)
    sources.write_sketches(sketches, str(tmp_path / "s"), ("g",))
    back = sources.read_sketches(spark, str(tmp_path / "s"))
    assert {r["g"]: list(r["words"]) for r in back.collect()} == {r["g"]: list(r["words"]) for r in sketches.collect()}
    other = build.sketch(spark.range(9).select(F.lit(1).alias("g"), "id"), "id", ["g"], 512)
    with pytest.raises(Exception, match="different formats"):
        sources.compatible(sketches, other).collect()


def test_dense_states_of_a_simulated_sketch():
    first = methods.first_seen(np.random.default_rng(1), 1408)
    cells = methods.dense56(first, 50_000.0)
    assert cells.sum() == 1408 and abs(tensor.dense_ml(cells[None], 1408)[0] / 50_000 - 1) < 0.08
    assert abs(tensor.components(cells[None], 1408)["hybrid"][0] / 50_000 - 1) < 0.08
    assert abs(methods.martingale(methods.first_seen(np.random.default_rng(2), 256, 4), np.array([5e4]))[0] / 5e4 - 1) < 0.2


def test_encodings_hold_what_they_can():
    top = np.array([0, 3, 7, 20, 1])
    assert methods.max_only("tailcut4", top)[0].tolist() == [0, 3, 7, 15, 1]
    assert methods.max_only("offset3", top) [1] == 2 and (methods.max_only("offset3", top)[0] == top).all()
    assert methods.max_only("nibble4", top)[1] == 1


def test_two_bit_sketch_counts_half_of_the_first_elements():
    """The threshold starts at level one: a single element is counted twice or not at all."""
    got = [methods.twobit(np.random.default_rng(i), methods.first_seen(np.random.default_rng(i + 99), 4096), np.array([1.0, 10.0]), False) for i in range(300)]
    one, ten = (np.array(x) for x in zip(*got, strict=True))
    assert np.abs(one - 1).min() > 0.9
    assert np.abs(ten / 10 - 1).mean() == pytest.approx(0.247, abs=0.04)


def test_measures():
    assert metrics.mvp(0.0163 / metrics.MAE_PER_RMSE, 1024) == pytest.approx(3.42, abs=0.01)
    assert 100 * metrics.predicted_rmse(256) == pytest.approx(2.148, abs=0.002)
    assert 100 * metrics.relative_delta(1.63, 1.71) == pytest.approx(-4.7, abs=0.05)
    assert metrics.writes_per_register(20e6 / 2816, 2) == pytest.approx(10.76, abs=0.01)
    assert metrics.mae_to_rmse(1.71) == pytest.approx(2.143, abs=0.01)


def test_saturation_counts(spark):
    planted = spark.createDataFrame([("x", i, 1 << (2 if i < 9 else 30)) for i in range(11)], "g string, bucket int, bitmap long")
    row = experiments.saturation(planted, ["g"], 11).first()
    assert (row["filled"], row["without_history"], row["saturated"]) == (11, 2, 2)


def test_sequential_merge_of_one_group(spark):
    rows = spark.range(5_000).select(F.lit("a").alias("g"), "id").repartition(3)
    merged = sequential.merge_sketches(sequential.sketch_partitions(rows, "id", ["g"], 352), ["g"])
    assert merged.count() == 1
