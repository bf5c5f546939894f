"""Monte-Carlo state histograms by first-arrival times.

Level k of a register is first seen after an exponential time with rate 2**-(k+1) / B
elements, so one draw per (register, level) gives the sketch at every cardinality; no
element is ever hashed. One task simulates whole instances from their own seeds.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LEVELS = 48
STRIDE = 1000


def histograms(spark: SparkSession, instances: int, registers: int, loads: tuple[float, ...], seed: int = 1, keys: DataFrame | None = None) -> DataFrame:
    """(g, z, hist, n) with g = instance * 1000 + checkpoint number, at loads * B elements.
    ``keys`` as in ``methods_at``."""
    assert len(loads) < STRIDE
    parts = min(instances, 4 * spark.sparkContext.defaultParallelism)
    rate = 2.0 ** -(np.arange(LEVELS) + 1)

    def rows(i: int, first: np.ndarray) -> pa.RecordBatch:
        g, z, h, n = [], [], [], []
        for c, load in enumerate(loads):
            seen = first <= load
            top = np.where(seen.any(1), seen.shape[1] - 1 - seen[:, ::-1].argmax(1), -1)
            row = np.arange(registers)
            one, two = seen[row, np.maximum(top - 1, 0)] & (top >= 1), seen[row, np.maximum(top - 2, 0)] & (top >= 2)
            code, many = np.unique(np.where(top >= 0, top * 4 + 2 * one + two, -1), return_counts=True)
            code, many = code[code >= 0], many[code >= 0]
            g += [i * STRIDE + c] * len(code)
            z += (code // 4).tolist()
            h += (code % 4).tolist()
            n += many.tolist()
        return pa.RecordBatch.from_arrays([pa.array(g, pa.int64()), pa.array(z, pa.int32()), pa.array(h, pa.int32()), pa.array(n, pa.int64())], ["g", "z", "hist", "n"])

    if keys is not None:
        from . import methods

        def each(i: int, n: int, begun: list[np.ndarray]) -> pa.Table:
            first = methods.first_seen(np.random.default_rng([seed, i]), registers, begun=begun[0], n=n)
            return pa.Table.from_batches([rows(i, first / registers)])

        return by_instance(keys, instances, [(registers, 1)], seed, each, "g long, z int, hist int, n long")

    def run(batches):
        for batch in batches:
            for i in batch.column(0).to_pylist():
                rng = np.random.default_rng([seed, i])
                yield rows(i, rng.exponential(1.0, (registers, LEVELS)) / rate)

    return spark.range(0, instances, 1, parts).mapInArrow(run, "g long, z int, hist int, n long")


#: elements mixed at a time, parts of a table
TURN, PARTS = 1 << 16, 16


def first_arrivals(keys: DataFrame, instances: int, shapes: list[tuple[int, int]], seed: int) -> DataFrame:
    """(instance, n, begun) of a table's distinct elements (k), in parts: ``begun`` packs, for
    each of the ``shapes`` (registers, parts of a level), the places of first arrivals, of an
    instance that is the mixer with a seed of its own. Places are those in the order of k; the
    minimum over the parts, and the sum of their n, are those of the table."""
    from . import methods
    from .functions import hashing
    from .operators import build

    placed = build.numbered(keys.select("k").where("k is not null").distinct(), F.floor(F.col("k") / 4096), "k").select("k", "rn")

    def run(batches):
        k, place = [], []
        for batch in batches:
            k.append(batch.column(0).to_numpy())
            place.append(batch.column(1).to_numpy())
        if not k:
            return
        k, place = np.concatenate(k), np.concatenate(place)
        order = np.argsort(place)
        k, place = k[order], place[order].astype(float)
        for i in range(instances):
            begun = [np.full(b * methods.LEVELS * split, np.inf) for b, split in shapes]
            word = hashing.signed((seed * 1_000_003 + i + 1) * hashing.SEED_STEP)
            for at in range(0, len(k), TURN):
                h = hashing.mix64_np(k[at : at + TURN] ^ word)
                z = hashing.rank_np(h)
                for t, (b, split) in zip(begun, shapes, strict=True):
                    methods.note(t, h, z, place[at : at + TURN], b, split)
            packed = pa.compress(np.concatenate(begun).astype(np.float64).tobytes(), codec="zstd", asbytes=True)
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int64()), pa.array([len(k)], pa.int64()), pa.array([packed], pa.binary())], ["instance", "n", "begun"])

    return placed.repartition(PARTS).mapInArrow(run, "instance long, n long, begun binary")


def by_instance(keys: DataFrame, instances: int, shapes: list[tuple[int, int]], seed: int, each, schema: str) -> DataFrame:
    """Rows that ``each(instance, n, [begun of each shape])`` gives, once for every instance."""
    from . import methods

    sizes = [b * methods.LEVELS * split for b, split in shapes]

    def merge(table: pa.Table) -> pa.Table:
        whole = np.full(sum(sizes), np.inf)
        for x in table["begun"]:
            raw = pa.decompress(x.as_py(), decompressed_size=8 * len(whole), codec="zstd", asbytes=True)
            np.minimum(whole, np.frombuffer(raw), out=whole)
        n = sum(table["n"].to_pylist())
        return each(table["instance"][0].as_py(), n, np.split(whole, np.cumsum(sizes)[:-1]))

    return first_arrivals(keys, instances, shapes, seed).groupBy("instance").applyInArrow(merge, schema)


def errors(estimates: DataFrame, registers: int, loads: tuple[float, ...], components: tuple[str, ...]) -> DataFrame:
    """(estimator, instance, checkpoint, truth, estimate) rows of simulated estimates."""
    truth = F.element_at(F.array(*[F.lit(float(x * registers)) for x in loads]), (F.col("g") % STRIDE + 1).cast("int"))
    pairs = F.explode(F.array(*[F.struct(F.lit(c).alias("estimator"), F.col(c).alias("estimate")) for c in components]))
    rows = estimates.select(F.floor(F.col("g") / STRIDE).alias("instance"), truth.alias("truth"), pairs.alias("p"))
    return rows.select("p.estimator", "instance", F.col("truth").alias("checkpoint"), "truth", F.coalesce("p.estimate", F.lit(0.0)).alias("estimate"))


#: registers of each method at one KB
ONE_KB = {"hybrid": 1408, "dense_ml": 1408, "wide_ml": 256, "tailcut4": 2048, "offset3": 2048, "nibble4": 2048, "twobit": 4096, "byte_hist": 1024, "hll6": 1280, "floor4": 2048, "floor6h": 1280, "martingale": 256}
_SIM = "instance long, estimator string, registers int, checkpoint double, truth double, estimate double, outside long"


def going_on(marks: tuple[float, ...], n: float) -> tuple[float, ...]:
    """Checkpoints that go on at their last ratio up to and with the n-th element."""
    out = list(marks)
    while out[-1] < n:
        out.append(min(float(n), out[-1] * marks[-1] / marks[-2]))
    return tuple(out)


def methods_at(spark: SparkSession, sizes: list[tuple[str, int]], marks: tuple[float, ...], instances: int, seed: int = 7, repeats: bool = False, keys: DataFrame | None = None) -> DataFrame:
    """(instance, estimator, registers, checkpoint, truth, estimate, outside) of so many
    registers of each method, in encodings as they would be stored, at all checkpoints.
    ``outside``: entries of exception maps. With ``keys`` (k), an instance is the table's distinct
    elements under a mixer of its own, which the model goes on from after the last, and marks go
    on to the last; without, a task simulates whole instances from their seeds."""
    from . import methods
    from .operators import tensor

    def split_of(name: str) -> int:
        return 4 if name in ("wide_ml", "martingale") else 1

    def one(name: str, registers: int, rng: np.random.Generator, at: np.ndarray, begun: np.ndarray | None = None, n: int = 0):
        first = methods.first_seen(rng, registers, split_of(name), begun=begun, n=n)
        outside = [0] * len(at)
        if name == "twobit":
            return methods.twobit(rng, first, at, repeats), outside
        if name == "martingale":
            return methods.martingale(first, at), outside
        if name in ("hybrid", "dense_ml", "floor4", "floor6h"):
            cells = np.stack([methods.dense56(first, c) if name in ("hybrid", "dense_ml") else methods.shared_floor(first, c, name == "floor6h") for c in at])
            if name == "dense_ml":
                return tensor.dense_ml(cells, registers), outside
            return tensor.components(cells, registers)["tiered_lc" if name == "floor4" else "hybrid"], outside
        if name in ("wide_ml", "byte_hist"):
            return [getattr(methods, name)(first, c) for c in at], outside
        kept = [methods.max_only(name, methods.levels(first, c)[0]) for c in at]
        return [methods.hll(top) for top, _ in kept], [n for _, n in kept]

    def rows(i: int, name: str, registers: int, at: np.ndarray, got, outside) -> pa.RecordBatch:
        n = len(at)
        columns = [np.full(n, i), [name] * n, np.full(n, registers, np.int32), at, at, np.asarray(got, float), np.asarray(outside, np.int64)]
        return pa.RecordBatch.from_arrays([pa.array(x) for x in columns], [x.split()[0] for x in _SIM.split(", ")])

    if keys is not None:
        shapes = list(dict.fromkeys((b, split_of(name)) for name, b in sizes))

        def each(i: int, n: int, begun: list[np.ndarray]) -> pa.Table:
            at = np.array(going_on(marks, n), float)
            return pa.Table.from_batches([rows(i, name, b, at, *one(name, b, np.random.default_rng([seed, i, k]), at, begun[shapes.index((b, split_of(name)))], n)) for k, (name, b) in enumerate(sizes)])

        return by_instance(keys, instances, shapes, seed, each, _SIM)

    at = np.array(marks, float)

    def run(batches):
        for batch in batches:
            for i in batch.column(0).to_pylist():
                for k, (name, registers) in enumerate(sizes):
                    yield rows(i, name, registers, at, *one(name, registers, np.random.default_rng([seed, i, k]), at))

    parts = min(instances, 4 * spark.sparkContext.defaultParallelism)
    return spark.range(0, instances, 1, parts).mapInArrow(run, _SIM)
