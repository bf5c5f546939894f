"""What plans cost the driver before any task runs."""

import numpy as np
from pyspark.sql import functions as F

from densecount import workloads
from densecount.functions import hashing


def planned_mb(spark, df) -> float:
    """MB that the JVM allocates in planning."""
    threads = spark._jvm.java.lang.management.ManagementFactory.getThreadMXBean()
    before = sum(x for x in threads.getThreadAllocatedBytes(threads.getAllThreadIds()) if x > 0)
    df._jdf.queryExecution().executedPlan()
    return (sum(x for x in threads.getThreadAllocatedBytes(threads.getAllThreadIds()) if x > 0) - before) / 1e6


def test_pool_draws_plan_in_little_memory(spark):
    part = spark.range(3000).select((F.col("id") * 7).alias("p_partkey"))
    draws = workloads.pool_draws(part)
    mb = planned_mb(spark, draws)
    assert mb < 500, mb
    ids = np.arange(3000 * workloads.DRAWS)
    u = [hashing.mix64_np(ids ^ hashing.signed(s * hashing.SEED_STEP)) // np.uint64(2048) % np.uint64(3000) for s in (11, 12)]
    assert sorted(r["k"] for r in draws.collect()) == sorted((np.minimum(*u) * np.uint64(7)).tolist())
