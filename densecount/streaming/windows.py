"""Distinct counts over streams: windowed bitmaps, and packed sketches as keyed state."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import build


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    events = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return events.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need an instant


def windowed_bitmaps(events: DataFrame, key: str, width: str, registers: int, slide: str | None = None, late: str = "1 hour", by: tuple[str, ...] = ()) -> DataFrame:
    """window, by..., bucket, bitmap: state is at most a bitmap per register and window, and
    events that come again change nothing."""
    rows = events.withWatermark("ts", late).select("ts", *by, F.col(key).alias("_k"))
    hashed = build.hashed(rows, "_k", ["ts", *by], registers)
    return hashed.groupBy(F.window("ts", width, slide or width), *by, "bucket").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("z"))).alias("bitmap"))


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))


ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_available(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over what there is and return its result. Rows that are appended grow with
    the input, so executors write them as Parquet beside the checkpoint; the other modes hold a
    row per register and window, or per group, and keep them in memory."""
    spark, name = stream.sparkSession, f"stream_{uuid.uuid4().hex}"
    base = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="densecount-stream-")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/{name}").trigger(availableNow=True)
    if mode == "append":
        started = _with_state_on_disk(spark, writer.format("parquet").option("path", f"{base}/{name}-out").start)
        started.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/{name}-out")
    writer.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def _with_state_on_disk(spark: SparkSession, start):
    """Start a stream, which copies the session's settings, with RocksDB as its state store:
    all that the watermark has not closed yet need not fit the executors' heaps."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key, None)
    spark.conf.set(key, ROCKSDB)
    try:
        return start()
    finally:
        spark.conf.set(key, before) if before else spark.conf.unset(key)


def stateful_sketch(events: DataFrame, group: str, key: str, registers: int) -> DataFrame:
    """(group, adds, estimate) after each batch: one packed sketch per group is the state, and
    rows below its floor are dropped before any register is touched."""
    import numpy as np

    from ..operators.kernel import hybrid_of
    from ..operators.sequential import Sketch
    from ..functions import codec

    rows = build.hashed(events, key, [group], registers).select(group, "bucket", "z")

    def step(key_: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.exists:
            words, floor, adds = state.get
            s = Sketch.of(np.array(words, np.int64), registers, floor)
            s.adds = adds
        else:
            s = Sketch(registers)
        for b in batches:
            s.add(b["bucket"].to_numpy().astype(np.int64), b["z"].to_numpy().astype(np.int64))
        state.update((codec.pack(s.states()).tolist(), int(s.floor), int(s.adds)))
        yield pd.DataFrame({group: [key_[0]], "adds": [s.adds], "estimate": [hybrid_of(s.z, s.history, registers, s.floor)]})

    return rows.groupBy(group).applyInPandasWithState(
        step, f"{group} string, adds long, estimate double", "words array<long>, floor int, adds long", "update", GroupStateTimeout.NoTimeout
    )
