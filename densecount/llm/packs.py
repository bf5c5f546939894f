"""Documents as compressed blocks: a few large rows that can be joined by block number."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from . import store, textops

SCHEMA = store.schema("block long, ids binary, known binary, offsets binary, bytes long, texts binary")


def packs(docs: DataFrame, block_bytes: int = 4 << 20, rows: int = 30_000) -> DataFrame:
    """(doc_id, text) rows in blocks, each with a number of its own; settle before use, as
    numbers follow the partitions."""

    def run(batches):
        base = TaskContext.get().partitionId() << 32
        for k, (batch, data, offsets) in enumerate(textops.blocks(batches, block_bytes, rows=rows)):
            ids = batch.column(0).to_pylist()
            yield store.rows(
                SCHEMA, block=[base + k], ids=[store.pack(np.array([x or 0 for x in ids], np.int64))], known=[store.pack(np.array([x is not None for x in ids]))],
                offsets=[store.pack(offsets)], bytes=[len(data)], texts=[pa.compress(data.tobytes(), codec="zstd", asbytes=True)],
            )

    return docs.mapInArrow(run, SCHEMA)


class Pack:
    def __init__(self, row: dict) -> None:
        self.block, size = row["block"], row["bytes"]
        self.ids, self.known = store.unpack(row["ids"], np.int64), store.unpack(row["known"], bool)
        self.offsets = store.unpack(row["offsets"], np.int64)
        raw = pa.decompress(row["texts"], decompressed_size=size, codec="zstd", asbytes=True) if size else b""
        self.data = np.frombuffer(raw, np.uint8)
