"""Set sizes from sketches, and an as-of join."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import build, estimators


def sizes(a: DataFrame, b: DataFrame, registers: int) -> DataFrame:
    """One row: union, intersection and difference of two sets held as bitmaps. The union is
    an OR; the others follow by inclusion and exclusion, so their error is that of the union
    (large when the sets are very unequal)."""
    union = build.merge_bitmaps(a.unionByName(b))
    tagged = None
    for name, part in (("a", a), ("b", b), ("u", union)):
        rows = part.select(F.lit(name).alias("g"), "bucket", "bitmap")
        tagged = rows if tagged is None else tagged.unionByName(rows)
    e = estimators.hybrid(build.state_histogram(tagged, ["g"]), registers)
    pick = {n: F.coalesce(F.max(F.when(F.col("g") == n, F.col("estimate"))), F.lit(0.0)) for n in ("a", "b", "u")}
    one = e.agg(*[c.alias(n) for n, c in pick.items()])
    return one.select(F.col("u").alias("union_estimate"), F.greatest(F.col("a") + F.col("b") - F.col("u"), F.lit(0.0)).alias("intersect_estimate"), F.greatest(F.col("u") - F.col("b"), F.lit(0.0)).alias("except_estimate"))


def asof(left: DataFrame, right: DataFrame, at: str, value: str, period: str = "month") -> DataFrame:
    """Left rows with the last right value at or before them (null if there is none).

    Rows of both sides are ordered within periods only; what a period starts with is the last
    value of the periods before, found on one row per period."""
    marks = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_left"))
    points = right.select(*[F.lit(None).cast(left.schema[c].dataType).alias(c) if c != at else F.col(at) for c in left.columns], F.col(value), F.lit(0).alias("_left"))
    both = marks.unionByName(points).withColumn("_period", F.date_trunc(period, at))
    inside = W.partitionBy("_period").orderBy(at, "_left").rowsBetween(W.unboundedPreceding, 0)
    carried = both.withColumn("_in", F.last(value, ignorenulls=True).over(inside))
    ends = right.withColumn("_period", F.date_trunc(period, at)).groupBy("_period").agg(F.max_by(value, at).alias("_end"))
    periods = both.select("_period").distinct().join(ends, "_period", "left")
    before = periods.withColumn("_before", F.last("_end", ignorenulls=True).over(W.orderBy("_period").rowsBetween(W.unboundedPreceding, -1)))
    joined = carried.where("_left = 1").join(before.select("_period", "_before"), "_period", "left")
    return joined.select(*left.columns, F.coalesce("_in", "_before").alias(value))
