"""Accuracy and cost measures over (estimator, checkpoint, truth, estimate) rows."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

MAE_PER_RMSE = math.sqrt(2 / math.pi)


def per_checkpoint(results: DataFrame, by: tuple[str, ...] = ("estimator",)) -> DataFrame:
    """Mean absolute relative error, bias and RMSE of each checkpoint over its instances."""
    e = F.col("estimate") / F.col("truth") - 1
    return results.groupBy(*by, "checkpoint").agg(F.avg(F.abs(e)).alias("mae"), F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"))


def summary(results: DataFrame, by: tuple[str, ...] = ("estimator",)) -> DataFrame:
    """Width-weighted, log-weighted and peak error of each estimator: checkpoints weigh as the
    interval to the next one, or alike."""
    each = per_checkpoint(results, by)
    step = F.lead("checkpoint").over(W.partitionBy(*by).orderBy("checkpoint")) - F.col("checkpoint")
    return each.withColumn("width", step).groupBy(*by).agg(
        (F.sum(F.col("mae") * F.col("width")) / F.sum(F.when(F.col("width").isNotNull(), F.col("width")))).alias("width_w"),
        F.avg("mae").alias("log_w"),
        F.max("mae").alias("peak"),
        F.sqrt(F.avg(F.col("rmse") * F.col("rmse"))).alias("rmse"),
    )


def mae_to_rmse(mae: float) -> float:
    return mae / MAE_PER_RMSE


def mvp(rmse: float, memory_bytes: int) -> float:
    """Memory-variance product: squared relative error times bits."""
    return rmse * rmse * memory_bytes * 8


def predicted_rmse(registers: int, d: int = 24, product: float = 3.78) -> float:
    """Theory of the wide register: its bits count t + 6 + d = 8 + d at t = 2."""
    return math.sqrt(product / ((8 + d) * registers))


def relative_delta(a: float, b: float) -> float:
    return a / b - 1


def writes_per_register(load: float, depth: int, step: float = 1.0) -> float:
    """Expected changes of a register at a load (elements per register), with ``depth``
    history levels; ``step`` levels per update value (0.25 for the wide register's four)."""
    total, k = 0.0, 0
    while k < 64 / step:
        own = 2.0 ** -(math.floor(k * step) + 1) * step
        above = 2.0 ** -(math.floor((k + depth) * step) + 1)
        rate = own + above
        total += own / rate * -math.expm1(-load * rate)
        k += 1
    return total


def density_table(spark) -> DataFrame:
    from .baselines import AT_ONE_KB

    rows = [(n, r, float(b), bool(m), round(8192 / r, 4)) for n, (r, b, m) in AT_ONE_KB.items()]
    return spark.createDataFrame(rows, "estimator string, registers int, bits_per_register double, exception_map boolean, bits_used double")
