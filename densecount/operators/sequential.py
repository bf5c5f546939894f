"""The order-dependent builder: one pass, floors that rise, counters, merges.

Rows are dealt with in Arrow batches; within a chunk the floor is frozen, so a chunk is one
vectorised OR per register, and the floor is raised after it. What a sketch drops early
(history above tier 13, exponents above 18) can make it differ from the relational build in
the few registers that ever stood that high.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import codec
from . import build

CHUNK = 8192


class Sketch:
    """Registers as level windows above a floor (bit r: exponent r was seen)."""

    def __init__(self, registers: int, floor: int = -1, levels: np.ndarray | None = None) -> None:
        self.registers, self.floor = registers, floor
        #: highest rank of each register, -1 if empty, and its two history bits
        self.z = np.full(registers, -1, np.int64) if levels is None else levels[0]
        self.history = np.zeros(registers, np.int64) if levels is None else levels[1]
        self.adds = self.reads = self.writes = 0

    def add(self, bucket: np.ndarray, z: np.ndarray) -> None:
        for at in range(0, len(z), CHUNK):
            self._chunk(bucket[at : at + CHUNK], z[at : at + CHUNK])

    def _chunk(self, bucket: np.ndarray, z: np.ndarray) -> None:
        self.adds += len(z)
        ok = z >= self.floor
        bucket, z = bucket[ok], z[ok]
        self.reads += len(z)
        # a read writes where its level is new within the window of what came before
        order = np.lexsort((np.arange(len(z)), bucket))
        for b, level in self._new(bucket[order], z[order]):
            top, h = self.z[b], self.history[b]
            if level > top:
                gap = level - top
                self.history[b] = (2 if gap == 1 and top >= 0 else 0) | (h >> 1 if gap == 1 else 1 if gap == 2 and top >= 0 else 0)
                self.z[b] = level
                if level - self.floor > codec.HISTORY_LIMIT:
                    self.history[b] = 0
                self.writes += 1
            elif top - level in (1, 2) and top - self.floor <= codec.HISTORY_LIMIT:
                bit = 2 if top - level == 1 else 1
                if not h & bit:
                    self.history[b] = h | bit
                    self.writes += 1
        self._promote()

    def _new(self, bucket: np.ndarray, z: np.ndarray):
        """Candidates that can change a register, in order of arrival within each."""
        top, h = self.z[bucket], self.history[bucket]
        d = top - z
        maybe = (d < 0) | ((d == 1) & (h & 2 == 0)) | ((d == 2) & (h & 1 == 0))
        return zip(bucket[maybe].tolist(), z[maybe].tolist(), strict=True)

    def _promote(self) -> None:
        self.floor = max(self.floor, int(self.z.min()) - codec.MARGIN) if self.registers and self.z.min() >= 0 else self.floor

    def states(self) -> np.ndarray:
        r = np.where(self.z < 0, 0, self.z - self.floor)
        return codec.states_np(r, np.where(r > codec.HISTORY_LIMIT, 0, self.history))

    @classmethod
    def of(cls, words: np.ndarray, registers: int, floor: int) -> Sketch:
        states = codec.unpack(words, registers)
        z = np.where(states == 0, -1, codec.EXPONENT[states] + floor)
        return cls(registers, floor, (z, codec.HISTORY[states].astype(np.int64)))

    def merge(self, other: Sketch) -> Sketch:
        """Levels that either has seen, above the larger floor, floor raised again."""
        top = np.maximum(self.z, other.z)
        history = np.zeros_like(top)
        for x in (self, other):
            gap = top - x.z
            history |= np.where(x.z < 0, 0, np.where(gap == 0, x.history, np.where(gap == 1, 2 | (x.history >> 1), np.where(gap == 2, 1, 0))))
        out = Sketch(self.registers, max(self.floor, other.floor), (top, np.where(top < 0, 0, history)))
        out._promote()
        for name in ("adds", "reads", "writes"):
            setattr(out, name, getattr(self, name) + getattr(other, name))
        return out


def _schema(df: DataFrame, by: Sequence[str]) -> T.StructType:
    own = [T.StructField("floor", T.IntegerType()), T.StructField("words", T.ArrayType(T.LongType()))] + [T.StructField(n, T.LongType()) for n in ("adds", "reads", "writes")]
    return T.StructType([df.schema[b] for b in by] + own)


def sketch_partitions(df: DataFrame, key: str, by: Sequence[str] = (), registers: int = 1408, seed: int = 0) -> DataFrame:
    """One sketch per (task, group), built in the order rows arrive."""
    rows = build.hashed(df, key, by, registers, seed).select(*by, "bucket", "z")
    schema = _schema(rows, by)

    def run(batches):
        held: dict[tuple, Sketch] = {}
        for batch in batches:
            bucket, z = batch["bucket"].to_numpy().astype(np.int64), batch["z"].to_numpy().astype(np.int64)
            if not by:
                held.setdefault((), Sketch(registers)).add(bucket, z)
                continue
            frame = pd.DataFrame({b: batch[b].to_pandas() for b in by})
            for g, at in frame.groupby(list(by), sort=False, dropna=False).indices.items():
                g = g if isinstance(g, tuple) else (g,)
                held.setdefault(g, Sketch(registers)).add(bucket[at], z[at])
        if held:
            keys, sketches = zip(*held.items(), strict=True)
            columns = {b: [k[i] for k in keys] for i, b in enumerate(by)}
            yield _rows(schema, columns, sketches)

    return rows.mapInArrow(run, schema)


def _rows(schema: T.StructType, columns: dict, sketches: Sequence[Sketch]) -> pa.RecordBatch:
    from pyspark.sql.pandas.types import to_arrow_schema

    columns = columns | {"floor": [s.floor for s in sketches], "words": [codec.pack(s.states()).tolist() for s in sketches]} | {n: [getattr(s, n) for s in sketches] for n in ("adds", "reads", "writes")}
    kind = to_arrow_schema(schema)
    return pa.RecordBatch.from_arrays([pa.array([x.item() if hasattr(x, "item") else x for x in columns[f.name]], f.type) for f in kind], schema=kind)


def merge_sketches(sketches: DataFrame, by: Sequence[str] = (), registers: int = 1408, fan_in: int = 256) -> DataFrame:
    """One sketch per group: first within salted parts of a group, then across them, so no
    task holds more than its share of a hot group."""
    schema = _schema(sketches, by)

    def run(table: pa.Table) -> pa.Table:
        out = None
        for row in table.to_pylist():
            s = Sketch.of(np.array(row["words"], np.int64), registers, row["floor"])
            s.adds, s.reads, s.writes = row["adds"], row["reads"], row["writes"]
            out = s if out is None else out.merge(s)
        first = table.slice(0, 1).to_pylist()[0]
        return pa.Table.from_batches([_rows(schema, {b: [first[b]] for b in by}, [out])])

    salted = sketches.withColumn("_salt", F.pmod(F.xxhash64("words", "adds"), F.lit(fan_in)))
    part = salted.groupBy(*by, "_salt").applyInArrow(run, schema)
    return part.groupBy(*by).applyInArrow(run, schema)
