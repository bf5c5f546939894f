"""Simulated instances whose elements are the rows of a given table."""

import numpy as np
import pytest

import __spark_entry__ as entry
from densecount import methods, simulate
from densecount.functions import hashing


@pytest.mark.parametrize("name", ["sim_components", "sim_equal_memory", "sim_equal_memory_holds", "sim_memory_scaling_holds", "sim_ranking_holds", "sim_repeated_holds"])
def test_reads_orders(spark, name):
    files = entry.queries()[name](spark, "/root/testdata/sf0.001").inputFiles()
    assert [f.rsplit("/", 1)[1] for f in files] == ["orders.parquet"]


def test_components_hold_needs_orders(spark, tmp_path):
    with pytest.raises(Exception, match="orders.parquet"):
        entry.queries()["sim_components_hold"](spark, str(tmp_path))


def test_first_arrivals_are_those_of_the_rows(spark):
    keys = spark.createDataFrame([(int(k),) for k in [*range(0, 30_000, 3), 6, 9]] + [(None,)], "k long")
    shapes = [(88, 1), (16, 4)]

    def each(i, n, begun):
        import pyarrow as pa

        return pa.table({"i": [i], "n": [n], "a": [begun[0].tolist()], "b": [begun[1].tolist()]})

    got = {r["i"]: r for r in simulate.by_instance(keys, 2, shapes, 7, each, "i long, n long, a array<double>, b array<double>").collect()}
    assert sorted(got) == [0, 1]
    k = np.arange(0, 30_000, 3)
    for i, r in got.items():
        assert r["n"] == len(k)
        h = hashing.mix64_np(k ^ hashing.signed((7_000_021 + i + 1) * hashing.SEED_STEP))
        z = hashing.rank_np(h)
        for (b, split), name in zip(shapes, "ab", strict=True):
            want = np.full(b * methods.LEVELS * split, np.inf)
            low = (h >> np.uint64(methods.baselines.LOW_SHIFT)).astype(int) % split
            np.minimum.at(want, ((h % np.uint64(b)).astype(int) * methods.LEVELS + z) * split + low, np.arange(1.0, len(k) + 1))
            assert (want == np.array(r[name])).all()


def test_given_elements_come_before_drawn_ones():
    begun = np.full(16 * methods.LEVELS, np.inf)
    begun[0] = 3.0
    first = methods.first_seen(np.random.default_rng(1), 16, begun=begun, n=50)
    assert first[0, 0] == 3.0 and (first.ravel()[1:] > 50).all()
    assert simulate.going_on((1.0, 2.0, 4.0), 20.0) == (1.0, 2.0, 4.0, 8.0, 16.0, 20.0)
    assert simulate.going_on((1.0, 2.0, 4.0), 3.0) == (1.0, 2.0, 4.0)
