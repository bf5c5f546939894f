"""Functions for SQL text: dc_estimate, dc_merge, the aggregates dc_sketch_agg and dc_merge_agg
with dc_size, and the table function dc_registers.

The aggregates are for small groups: Spark gives an aggregate in Python its whole group at
once. ``operators.build`` is the way for groups of any size; its sketches are the same.
Their value is an array of longs: registers, floor, then the words."""

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..functions import codec, hashing
from ..operators.kernel import hybrid_of
from ..operators.sequential import Sketch


@pandas_udf(T.DoubleType())
def dc_estimate(words: pd.Series, registers: pd.Series, floor: pd.Series) -> pd.Series:
    out = []
    for w, b, f in zip(words, registers, floor, strict=True):
        s = Sketch.of(np.asarray(w, np.int64), int(b), int(f))
        out.append(hybrid_of(s.z, s.history, int(b), int(f)))
    return pd.Series(out)


@pandas_udf(T.StructType([T.StructField("words", T.ArrayType(T.LongType())), T.StructField("floor", T.IntegerType())]))
def dc_merge(a: pd.Series, fa: pd.Series, b: pd.Series, fb: pd.Series, registers: pd.Series) -> pd.DataFrame:
    rows = []
    for wa, x, wb, y, r in zip(a, fa, b, fb, registers, strict=True):
        s = Sketch.of(np.asarray(wa, np.int64), int(r), int(x)).merge(Sketch.of(np.asarray(wb, np.int64), int(r), int(y)))
        rows.append((codec.pack(s.states()).tolist(), s.floor))
    return pd.DataFrame(rows, columns=["words", "floor"])


REGISTERS = 1408


def _array(s: Sketch) -> list[int]:
    return [s.registers, int(s.floor), *codec.pack(s.states()).tolist()]


def _sketch(array) -> Sketch:
    array = np.asarray(array, np.int64)
    return Sketch.of(array[2:], int(array[0]), int(array[1]))


@pandas_udf(T.ArrayType(T.LongType()))
def dc_sketch_agg(key: pd.Series) -> list:
    """The sketch of a group's integer keys; null keys count for nothing."""
    key = key.dropna().to_numpy().astype(np.int64)
    h = hashing.mix64_np(key)
    levels = np.zeros(REGISTERS, np.uint64)
    np.bitwise_or.at(levels, (h % np.uint64(REGISTERS)).astype(np.int64), np.uint64(1) << hashing.rank_np(h).astype(np.uint64))
    top = np.where(levels == 0, -1, 63 - hashing.rank_np(levels, 64))
    bit = lambda z: np.where(z >= 0, (levels >> np.maximum(z, 0).astype(np.uint64)) & np.uint64(1), 0).astype(np.int64)
    floor = max(-1, int(top.min()) - codec.MARGIN) if (top >= 0).all() else -1
    return _array(Sketch(REGISTERS, floor, (top, 2 * bit(top - 1) + bit(top - 2))))


@pandas_udf(T.ArrayType(T.LongType()))
def dc_merge_agg(sketch: pd.Series) -> list:
    """The union of a group's sketches; null ones count for nothing."""
    out = Sketch(REGISTERS)
    for i, x in enumerate(sketch.dropna()):
        out = out.merge(_sketch(x)) if i else _sketch(x)
    return _array(out)


@pandas_udf(T.DoubleType())
def dc_size(sketch: pd.Series) -> pd.Series:
    """The estimate of each sketch; 0 of an empty one."""
    out = []
    for x in sketch:
        s = _sketch(x)
        out.append(hybrid_of(s.z, s.history, s.registers, s.floor) if (s.z >= 0).any() else 0.0)
    return pd.Series(out, dtype=float)


@udtf(returnType=T.StructType([T.StructField("bucket", T.IntegerType()), T.StructField("state", T.IntegerType())]))
class DcRegisters:
    def eval(self, words, registers):
        for i, s in enumerate(codec.unpack(np.array(words, np.int64), registers).tolist()):
            yield i, s


def register(spark: SparkSession) -> None:
    spark.udf.register("dc_estimate", dc_estimate)
    spark.udf.register("dc_merge", dc_merge)
    spark.udf.register("dc_sketch_agg", dc_sketch_agg)
    spark.udf.register("dc_merge_agg", dc_merge_agg)
    spark.udf.register("dc_size", dc_size)
    spark.udtf.register("dc_registers", DcRegisters)
