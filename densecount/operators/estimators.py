"""Estimates from state histograms, as DataFrames."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..calibration import constants
from ..plans.estimate import COMPONENTS, BlendSpec
from . import tensor


def _cells(batch: pa.RecordBatch) -> np.ndarray:
    """Histograms of a batch as a tensor, from its lists of (z, hist, n)."""
    lists = batch.column(batch.schema.get_field_index("cells"))
    owner = np.repeat(np.arange(len(lists)), np.diff(np.asarray(lists.offsets)))
    z, hist, n = (np.asarray(x) for x in lists.flatten().flatten())
    out = np.zeros((len(lists), tensor.RANKS, 4))
    np.add.at(out, (owner, z, hist), n)
    return out


def all_components(hist: DataFrame, registers: int | None, blend: BlendSpec = BlendSpec(), ml: bool = False, **options) -> DataFrame:
    """(g, filled, floor, every component) from a histogram (g, z, hist, n), in one exchange
    of at most 256 rows a group. With ``registers`` None each group's own number is in a
    column ``registers``, which then stays; ``ml`` adds ``dense_ml``.

    Groups without a filled register have no rows and so no estimate; see ``or_zero``."""
    own = ["registers"] if registers is None else []
    lists = hist.groupBy("g", *own).agg(F.collect_list(F.struct(F.col("z").cast("int"), F.col("hist").cast("int"), F.col("n").cast("long"))).alias("cells"))
    names = [*COMPONENTS, *["dense_ml"] * ml]
    keys = [lists.schema[c] for c in ("g", *own)]
    schema = T.StructType([*keys, T.StructField("filled", T.LongType()), T.StructField("floor", T.IntegerType()), *[T.StructField(c, T.DoubleType()) for c in names]])

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                cells, b = _cells(part), np.asarray(part.column(1)) if own else registers
                out = tensor.components(cells, b, blend, **options) | ({"dense_ml": tensor.dense_ml(cells, b)} if ml else {})
                columns = [part.column(i) for i in range(len(keys))] + [pa.array(out["filled"].astype(np.int64)), pa.array(out["floor"].astype(np.int32))]
                columns += [pa.array(out[c], pa.float64(), mask=np.isnan(out[c])) for c in names]
                yield pa.RecordBatch.from_arrays(columns, schema.names)

    return lists.mapInArrow(run, schema)


def component(hist: DataFrame, name: str, registers: int | None, **options) -> DataFrame:
    if name not in COMPONENTS:
        raise ValueError(f"unknown estimator {name}")
    own = ["registers"] if registers is None else []
    return all_components(hist, registers, **options).select("g", *own, F.col(name).alias("estimate"))


def hybrid(hist: DataFrame, registers: int | None, blend: BlendSpec = BlendSpec()) -> DataFrame:
    return component(hist, "hybrid", registers, blend=blend)


def or_zero(groups: DataFrame, estimates: DataFrame) -> DataFrame:
    """Estimates for all groups (column g), 0 for those whose sketch is empty."""
    return groups.join(estimates, "g", "left").fillna(0.0, ["estimate"])


def bounds(estimate_: Column, registers: int, k: float = 2.0) -> tuple[Column, Column]:
    """estimate -+ k standard errors."""
    rmse = constants.ERROR_PER_ROOT / registers**0.5 / 0.798
    return estimate_ * (1 - k * rmse), estimate_ * (1 + k * rmse)
