"""Tables written once in the cluster's shared folder, and array columns as bytes."""

from __future__ import annotations

import re
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one only where that is unset and
    driver and executors are one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        own = spark.sparkContext._jsc.sc().getCheckpointDir()
        if own.isDefined():
            return own.get()
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = tempfile.mkdtemp(prefix="densecount-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def settle(df: DataFrame, tag: str = "step") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here, and a lost
    executor costs a re-read instead of a recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.settled_at = path
    return out


def drop(*settled: DataFrame) -> None:
    """Delete settled tables that nothing will read again."""
    for df in settled:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df.settled_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def documents(docs: DataFrame, *columns: str) -> DataFrame:
    """Only the columns an operator reads, so that other columns can have any names."""
    kinds = {"doc_id": "long", "text": "string"}
    return docs.select(*[F.col(f"`{c}`").cast(kinds[c]).alias(c) if c in kinds else F.col(f"`{c}`") for c in columns])


def pack(x: np.ndarray) -> bytes:
    """Byte planes of an array, compressed: equal high bytes cost next to nothing."""
    planes = np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.dtype.itemsize).T
    raw = planes.tobytes()
    return len(raw).to_bytes(8, "little") + (pa.compress(raw, codec="zstd", asbytes=True) if raw else b"")


def unpack(blob: bytes, dtype) -> np.ndarray:
    size = int.from_bytes(blob[:8], "little")
    if not size:
        return np.zeros(0, dtype)
    raw = pa.decompress(blob[8:], decompressed_size=size, codec="zstd", asbytes=True)
    dtype = np.dtype(dtype)
    planes = np.frombuffer(raw, np.uint8).reshape(dtype.itemsize, size // dtype.itemsize)
    return np.ascontiguousarray(planes.T).view(dtype).ravel()


def rows(schema: T.StructType, **columns) -> pa.RecordBatch:
    """A record batch in the order of ``schema``."""
    from pyspark.sql.pandas.types import to_arrow_schema

    kind = to_arrow_schema(schema)
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, f.type) for x, f in ((columns[f.name], f) for f in kind)], schema=kind)


_KINDS = {"long": T.LongType(), "int": T.IntegerType(), "string": T.StringType(), "double": T.DoubleType(), "boolean": T.BooleanType(), "binary": T.BinaryType()}


def each_row(batches):
    """Rows as dicts, one at a time, so that large cells are not held twice."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]


def schema(text: str, **nested: T.DataType) -> T.StructType:
    """``"a long, b string"`` as a schema, without a session; nested types by keyword."""
    plain = [T.StructField(*(lambda n, k: (n, _KINDS[k]))(*x.split())) for x in text.split(",")]
    return T.StructType(plain + [T.StructField(n, k) for n, k in nested.items()])
