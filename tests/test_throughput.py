"""Throughput runs build their sketches from all rows of given tables."""

import pytest

from densecount import experiments, sources

SF = "/root/testdata/sf0.001"
RUNS = {
    "bench_single": ["lineitem"],
    "bench_many": ["lineitem"],
    "bench_memory_sweep": ["lineitem"],
    "bench_pressure_sweep": ["lineitem"],
    "bench_cardinality_sweep": ["customer", "orders", "lineitem"],
}


@pytest.mark.parametrize("name", RUNS)
def test_all_rows_of_the_tables_are_added(spark, name):
    got = {r["adds"] for r in getattr(experiments, name)(spark, SF).collect()}
    assert got == {sources.table(spark, SF, t).count() for t in RUNS[name]}


@pytest.mark.parametrize("table", ["customer", "orders", "lineitem"])
def test_every_row_is_an_element(spark, table):
    keys = experiments.elements(spark, SF, table)
    assert keys.where("k is not null").count() == sources.table(spark, SF, table).count()
