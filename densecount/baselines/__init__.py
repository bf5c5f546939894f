"""Baseline sketches at equal memory, as relational plans.

All maximum-only ones share one aggregate, the highest rank per register; their encodings
(``encode``) are lossless for it, so tailcut4, offset3 and nibble4 estimate alike.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import lru_cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hashing
from ..operators import build

#: registers at a memory of one KB, bits per register, whether an exception map is needed
AT_ONE_KB = {
    "dense56": (1408, 5.82, False), "wide_ml": (256, 32.0, False), "tailcut4": (2048, 4.0, False), "offset3": (2048, 3.0, True), "nibble4": (2048, 4.0, True),
    "twobit": (4096, 2.0, False), "byte_hist": (1024, 8.0, False), "hll6": (1280, 6.4, False), "floor4": (2048, 4.0, False), "floor6h": (1280, 6.4, False),
}

#: published closed form for 8-bit registers with two history bits (fixed values): exponent
#: of the ranks' contributions and weights of the histories are re-derived in ``history_eta``
TAU = 0.8194911375910897


def registers(name: str, memory_bytes: int) -> int:
    return AT_ONE_KB[name][0] * memory_bytes // 1024


def max_ranks(df: DataFrame, key: str, by: Sequence[str], registers_: int, seed: int = 0) -> DataFrame:
    """by..., bucket, m: highest rank of each filled register."""
    return build.hashed(df, key, by, registers_, seed).groupBy(*by, "bucket").agg(F.max("z").alias("m"))


def hll_text(table: str, registers_: int, correct: bool = True) -> str:
    """SQL: harmonic-mean estimate per group of (g, bucket, m), linear counting below 2.5 B."""
    b = f"CAST({registers_} AS DOUBLE)"
    alpha = 0.7213 / (1 + 1.079 / registers_)
    raw = f"({alpha!r} * {b} * {b} / (s + ({b} - filled)))"
    return f"""
SELECT g, CASE WHEN {raw} <= 2.5 * {b} AND filled < {b} THEN {b} * ln({b} / ({b} - filled)) ELSE {raw} END AS estimate
FROM (SELECT g, CAST(count(*) AS DOUBLE) AS filled, sum(power(2.0, -m - 1)) AS s FROM {table} GROUP BY g) q"""


def hll(ranks: DataFrame, registers_: int) -> DataFrame:
    return ranks.sparkSession.sql(hll_text("{ranks}", registers_), ranks=ranks)


def encode(ranks: DataFrame, name: str, registers_: int) -> DataFrame:
    """(g, base, codes, exceptions): the register array of an encoding and what does not fit.

    tailcut4: offsets 0..15 above a base that all registers reach; offset3: 0..7 above the
    base, larger ones in the map; nibble4: rank + 1 capped at 15, larger ones in the map."""
    low = ranks.groupBy("g").agg(F.when(F.count(F.lit(1)) < registers_, -1).otherwise(F.min("m")).alias("base"))
    joined = ranks.join(low, "g")
    width = {"tailcut4": 15, "offset3": 7, "nibble4": 15}[name]
    code = F.col("m") + 1 if name == "nibble4" else F.col("m") - F.col("base")
    fits = code <= width if name == "offset3" else code < width if name == "nibble4" else F.lit(True)
    kept = F.when(fits, F.least(code, F.lit(width))).otherwise(width)
    entry = F.struct("bucket", kept.cast("int").alias("code"))
    rest = F.struct("bucket", F.col("m").cast("int").alias("m"))
    return joined.withColumn("over", ~fits if name != "tailcut4" else code > width).groupBy("g", "base").agg(
        F.array_sort(F.collect_list(entry)).alias("codes"), F.map_from_entries(F.array_sort(F.collect_list(F.when(F.col("over"), rest)))).alias("exceptions")
    )


def decode(encoded: DataFrame, name: str) -> DataFrame:
    """(g, bucket, m) back from an encoding."""
    rows = encoded.select("g", "base", "exceptions", F.explode("codes").alias("c")).select("g", "base", "exceptions", "c.bucket", "c.code")
    plain = F.col("code") - 1 if name == "nibble4" else F.col("code") + F.col("base")
    return rows.select("g", "bucket", F.coalesce(F.try_element_at("exceptions", F.col("bucket")), plain).cast("int").alias("m"))


def byte_hist_text(levels: str, registers_: int) -> str:
    """SQL: remaining-area style closed form of (g, z, hist, n).

    Each register contributes eta(hist) * 2**(-tau * z); for a mean over filled and empty
    registers (empty ones at rank -1 with all history seen) the estimate is a power of it.
    eta and the factor come from the Poisson model at high load; below 3 B, linear counting."""
    tau, eta, factor = history_eta()
    b = f"CAST({registers_} AS DOUBLE)"
    whole = "(CASE WHEN z = 0 THEN 3 WHEN z = 1 THEN hist + 1 - hist % 2 ELSE hist END)"
    case = "(CASE " + " ".join(f"WHEN {whole} = {h} THEN {e!r}" for h, e in enumerate(eta)) + " END)"
    raw = f"({factor!r} * {b} * power((s + ({b} - filled) * {eta[3] * 2.0**tau!r}) / {b}, {-1 / tau!r}))"
    return f"""
SELECT g, CASE WHEN filled < {b} AND {b} * ln({b} / ({b} - filled)) < 3 * {b} THEN {b} * ln({b} / ({b} - filled)) ELSE {raw} END AS estimate
FROM (SELECT g, CAST(sum(n) AS DOUBLE) AS filled, sum(n * {case} * power(2.0, -{tau!r} * z)) AS s FROM {levels} GROUP BY g) q"""


@lru_cache(1)
def history_eta(tau: float = TAU) -> tuple[float, list[float], float]:
    """(tau, weights of histories 0..3, factor) with least variance for ranks to the power
    of tau, from the expected histogram over one octave."""
    import numpy as np

    from ..calibration import fit

    first, second = np.zeros(4), np.zeros(4)
    loads = 2.0 ** np.linspace(20, 21, 65)[:-1]
    for lam in loads:
        p, y = fit.expected_histogram(lam), lam**tau * 2.0 ** (-tau * fit.K)
        first += (p * y[:, None]).sum(0)
        second += (p * y[:, None] ** 2).sum(0)
    eta = first / second
    eta /= eta[3]
    mean = np.mean([np.log((fit.expected_histogram(lam) @ eta * 2.0 ** (-tau * fit.K)).sum()) + tau * np.log(lam) for lam in loads])
    return tau, [round(float(x), 9) for x in eta], round(float(np.exp(mean / tau)), 9)


#: where the low bits of an update value are taken from the hash
LOW_SHIFT = 17


# --- wide registers with a maximum-likelihood estimate ---------------------------------


def wide_registers(df: DataFrame, key: str, by: Sequence[str], registers_: int, seed: int = 0, t: int = 2, d: int = 24) -> DataFrame:
    """by..., bucket, u, below: highest update value and a bitmap of the d values under it.

    An update value is 2**t per rank plus t bits of the hash, plus one; partial aggregates
    keep distinct values only, at most 63 * 2**t per register."""
    rows = build.hashed(df, key, by, registers_, seed)
    low = F.pmod(F.shiftrightunsigned(F.col("h"), LOW_SHIFT), F.lit(1 << t))
    value = (F.col("z") * (1 << t) + low + 1).cast("int")
    values = rows.select(*by, "bucket", value.alias("v")).groupBy(*by, "bucket").agg(F.max("v").alias("u"), F.collect_set("v").alias("seen"))
    bit = lambda v: F.call_function("shiftleft", F.lit(1).cast("long"), F.col("u") - v - 1)
    near = F.filter("seen", lambda v: (v < F.col("u")) & (v >= F.col("u") - d))
    return values.select(*by, "bucket", "u", F.aggregate(near, F.lit(0).cast("long"), lambda x, v: x.bitwiseOR(bit(v))).alias("below"))


def _wide_sums(table: str, registers_: int, t: int, d: int) -> str:
    """CTEs al (g, alpha) and b (g, pv, bn) of the likelihood of (g, bucket, u, below).

    An element makes value v in its register with probability p(v) = 2**-(k+1) / 2**t at
    rank k. Values that were not seen, above the maximum and in the window, count in alpha,
    seen ones in bn by probability."""
    q = 1 << t

    def p(v: str) -> str:
        return f"(power(2.0, -floor(({v} - 1) / {float(q)}) - 1) / {float(q)})"

    above = f"(power(2.0, -floor((u - 1) / {float(q)}) - 1) * (1.0 + ({q} - 1 - ((u - 1) % {q})) / {float(q)}))"
    offsets = ", ".join(f"({i}, {1 << (i - 1)})" for i in range(1, d + 1))
    return f"""
WITH r AS (SELECT g, bucket, CAST(u AS INT) AS u, below FROM {table}),
w AS (SELECT r.g, r.u - o.i AS v, CASE WHEN (r.below & o.bit) <> 0 THEN 1 ELSE 0 END AS seen FROM r JOIN (SELECT i, bit FROM (VALUES {offsets}) AS t(i, bit)) o ON r.u - o.i >= 1),
a AS (SELECT g, sum({above}) + {float(registers_)} - count(*) AS alpha FROM r GROUP BY g),
a2 AS (SELECT g, sum(CASE WHEN seen = 0 THEN {p('v')} ELSE 0.0 END) AS alpha FROM w GROUP BY g),
b AS (SELECT g, pv, CAST(count(*) AS DOUBLE) AS bn FROM (SELECT g, {p('u')} AS pv FROM r UNION ALL SELECT g, {p('v')} AS pv FROM w WHERE seen = 1) s GROUP BY g, pv),
al AS (SELECT a.g, a.alpha + coalesce(a2.alpha, 0.0) AS alpha FROM a LEFT JOIN a2 ON a2.g = a.g)"""


LOW, HIGH, STEPS = -20.0, 50.0, 56  # bisection in log2 of the load


def wide_ml(wide: DataFrame, registers_: int, t: int = 2, d: int = 24) -> DataFrame:
    """Maximum-likelihood estimate per group of (g, bucket, u, below).

    The score sum bn * p / (exp(load * p) - 1) falls in the load; a fixed number of halvings
    finds where it equals alpha. A group is at most ``registers_`` rows."""
    import numpy as np
    import pyarrow as pa
    from pyspark.sql import types as T

    def solve(table: pa.Table) -> pa.Table:
        u, below = table["u"].to_numpy().astype(np.int64), table["below"].to_numpy()
        p = 2.0 ** (-np.floor((np.arange(0, 260) - 1) / (1 << t)) - 1) / (1 << t)
        alpha = np.sum(2.0 ** (-np.floor((u - 1) / (1 << t)) - 1) * (1 + ((1 << t) - 1 - (u - 1) % (1 << t)) / (1 << t))) + registers_ - len(u)
        v = u[:, None] - np.arange(1, d + 1)
        seen = (below[:, None] >> np.arange(d)) & 1 == 1
        alpha += p[v[(v >= 1) & ~seen]].sum()
        value, many = np.unique(p[np.concatenate([u, v[(v >= 1) & seen]])], return_counts=True)
        lo, hi = LOW, HIGH
        for _ in range(STEPS):
            x = 2.0 ** ((lo + hi) / 2)
            above = np.sum(many * value / np.expm1(np.minimum(x * value, 700.0))) > alpha
            lo, hi = ((lo + hi) / 2, hi) if above else (lo, (lo + hi) / 2)
        return pa.table({"g": table["g"].slice(0, 1), "estimate": pa.array([registers_ * 2.0 ** ((lo + hi) / 2)])})

    return wide.groupBy("g").applyInArrow(solve, T.StructType([wide.schema["g"], T.StructField("estimate", T.DoubleType())]))


def wide_ml_duck(table: str, registers_: int, t: int = 2, d: int = 24) -> str:
    sql = _wide_sums(table, registers_, t, d) + f", s0 AS MATERIALIZED (SELECT g, alpha, CAST({LOW} AS DOUBLE) AS lo, CAST({HIGH} AS DOUBLE) AS hi FROM al), bm AS MATERIALIZED (SELECT * FROM b)"
    for i in range(1, STEPS + 1):
        sql += f""",
s{i} AS MATERIALIZED (SELECT g, alpha, CASE WHEN f > alpha THEN (lo + hi) / 2 ELSE lo END AS lo, CASE WHEN f > alpha THEN hi ELSE (lo + hi) / 2 END AS hi FROM (
  SELECT s.g, s.alpha, s.lo, s.hi, sum(bn * pv / (exp(least(power(2.0, (s.lo + s.hi) / 2) * pv, 700.0)) - 1.0)) AS f FROM s{i - 1} s JOIN bm ON bm.g = s.g GROUP BY s.g, s.alpha, s.lo, s.hi) q)"""
    return sql + f"\nSELECT g, {float(registers_)} * power(2.0, (lo + hi) / 2) AS estimate FROM s{STEPS}"
