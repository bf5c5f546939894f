"""The estimators as one declarative plan over a state histogram.

Input: rows (g, z, hist, n): in group g, n registers have highest rank z and history hist.
The text uses only functions that Spark SQL and DuckDB share, so the same plan runs on both
engines; Catalyst sees one aggregate per group and one join with the 63 tiers, which is
limited to the tiers between a group's lowest and highest rank.
"""

from __future__ import annotations

from dataclasses import dataclass

from ..calibration import constants as K

COMPONENTS = ("linear", "tiered_lc", "history_count", "mean", "mean_hist", "state_sum", "state_sum_exact", "low_blend", "layered", "harmonic0", "harmonic2", "hybrid")


@dataclass(frozen=True)
class BlendSpec:
    """Thresholds in elements per register."""

    low: tuple[float, float] = (2, 6)
    ramp: tuple[float, float, float] = (0.5, 4.5, 0.5)
    harmonic: tuple[float, float] = (1, 6)
    mix: float = 0.5

    def scaled(self, by: float) -> BlendSpec:
        return BlendSpec(tuple(x * by for x in self.low), (self.ramp[0] * by, self.ramp[1] * by, self.ramp[2]), tuple(x * by for x in self.harmonic), self.mix)


def tiers(n: int = 63) -> str:
    return "(SELECT k FROM (VALUES " + ", ".join(f"({i})" for i in range(n)) + ") AS t(k))"


def _sigmoid_gauss(x: str, c: tuple[float, ...]) -> str:
    terms = [repr(c[0])] + [f"({c[1 + 3 * i]!r}) * tanh(({x} - ({c[2 + 3 * i]!r})) / ({c[3 + 3 * i]!r}))" for i in range(3)]
    terms += [f"({c[10 + 3 * i]!r}) * exp(-power(({x} - ({c[11 + 3 * i]!r})) / ({c[12 + 3 * i]!r}), 2))" for i in range(2)]
    return "(" + " + ".join(terms) + ")"


def _periodic(x: str, c: tuple[float, ...]) -> str:
    w = f"(2 * pi() * {x})"
    return f"(({c[0]!r}) - ({c[1]!r}) * exp(-({c[2]!r}) * {x}) + (({c[3]!r}) + ({c[4]!r}) * {x}) * sin{w} + (({c[5]!r}) + ({c[6]!r}) * {x}) * cos{w})"


def _seen(k: str) -> str:
    """Expected elements of level k, given that it was seen, at load lam."""
    mu = f"(lam * power(2.0, -({k}) - 1))"
    return f"({mu} / (1.0 - exp(-{mu})))"


#: history with levels below 0 counted as seen
_FULL = "(CASE WHEN z = 0 THEN 3 WHEN z = 1 THEN hist + 1 - hist % 2 ELSE hist END)"
_STATE = "(CASE WHEN z = 0 THEN 0 WHEN z = 1 THEN 1 + (CASE WHEN hist >= 2 THEN 1 ELSE 0 END) WHEN z = 2 THEN 3 + hist ELSE 7 + hist END)"


def text(hist: str, registers: int, blend: BlendSpec = BlendSpec(), sharpen: float = 4.5, min_empty: float = 0.5, history_sharpen: float = 2.0, polynomials: tuple = K.STATE_POLYNOMIALS) -> str:
    """SQL that returns (g, filled, every component) for the histogram table ``hist``."""
    b = f"CAST({registers} AS DOUBLE)"
    weight = "(CASE " + " ".join(f"WHEN {_FULL} = {h} THEN {w!r}" for h, w in enumerate(K.HISTORY_WEIGHTS)) + " END)"
    cubic = "(CASE " + " ".join(f"WHEN {_STATE} = {s} THEN (({c[3]!r} * lam + ({c[2]!r})) * lam + ({c[1]!r})) * lam + ({c[0]!r})" for s, c in enumerate(polynomials)) + " END)"
    exact = (
        f"({_seen('z')} + (CASE WHEN z >= 1 AND hist >= 2 THEN {_seen('z - 1')} ELSE 0.0 END) + (CASE WHEN z >= 2 AND hist % 2 = 1 THEN {_seen('z - 2')} ELSE 0.0 END)"
        " + (CASE WHEN z >= 3 THEN lam * (1.0 - power(2.0, 2 - z)) ELSE 0.0 END))"
    )

    def corrected(raw: str, cf: tuple[float, ...]) -> tuple[str, str]:
        first = f"({raw} * {_sigmoid_gauss('x0', cf)})"
        return first, f"(CASE WHEN tiered_lc > 10 * {b} THEN {raw} * {_sigmoid_gauss(f'(ln(greatest(one, 1e-9) / {b}) / ln(2.0))', cf)} ELSE one END)"

    m1, m2 = corrected("mean_raw", K.MEAN_CF)
    h1, h2 = corrected("mean_hist_raw", K.MEAN_HIST_CF)
    (l0, l1), (r0, r1, rw), (a0, a1) = blend.low, blend.ramp, blend.harmonic
    low_w = f"least(1.0, greatest(0.0, ln(greatest(tiered_lc, 1e-9) / ({l0} * {b})) / ln({l1 / l0!r})))"
    harm_w = f"least(1.0, greatest(0.0, ln(greatest(tiered_lc, 1e-9) / ({a0} * {b})) / ln({a1 / a0!r})))"
    ramp_w = f"({rw} * least(1.0, greatest(0.0, (low_blend / {b} - {r0}) / {r1 - r0!r})))"
    return f"""
WITH h AS (SELECT g, CAST(z AS INT) AS z, CAST(hist AS INT) AS hist, CAST(n AS DOUBLE) AS n FROM {hist}),
s AS (
  SELECT g, sum(n) AS filled, min(z) AS lo, max(z) AS hi,
         CASE WHEN sum(n) < {registers} THEN -1 ELSE greatest(-1, min(z) - 2) END AS floor,
         sum(n * power(2.0, -z)) AS s0, sum(n * power(2.0, -z) * {weight}) AS s1
  FROM h GROUP BY g
), v AS (
  SELECT s.g, t.k, max(s.hi) AS hi, {b} - sum(CASE WHEN h.z >= t.k THEN n ELSE 0.0 END) AS v,
         sum(CASE WHEN h.z - t.k IN (1, 2) AND h.z - s.floor <= 13 THEN n ELSE 0.0 END) AS eff,
         sum(CASE WHEN h.z - s.floor > 13 THEN 0.0 WHEN h.z - t.k = 1 AND hist < 2 THEN n WHEN h.z - t.k = 2 AND hist % 2 = 0 THEN n ELSE 0.0 END) AS unseen
  FROM s JOIN {tiers()} t ON t.k BETWEEN greatest(0, s.lo - 2) AND s.hi + 1 JOIN h ON h.g = s.g
  GROUP BY s.g, t.k
), e AS (
  SELECT g, k, v, eff, unseen, hi,
         CASE WHEN v >= 1 AND v <= {b} - 1 THEN ln({b} / v) END AS lam_t,
         CASE WHEN eff >= 8 AND unseen >= 1 AND unseen < eff THEN unseen / eff END AS p
  FROM v
), t AS (
  SELECT g,
         sum(power(sqrt(exp(lam_t) - 1.0) / (lam_t * sqrt({b})), -{sharpen}) * (k * ln(2.0) + ln({b}) + ln(lam_t))) / sum(power(sqrt(exp(lam_t) - 1.0) / (lam_t * sqrt({b})), -{sharpen})) AS log_lc,
         max(CASE WHEN k = hi THEN k * ln(2.0) + ln({b}) + ln(ln({b} / {min_empty})) END) AS log_guard,
         sum(power(sqrt((1.0 - p) / (p * eff)) / (-ln(p)), -{history_sharpen}) * ((k + 1) * ln(2.0) + ln({b}) + ln(-ln(p)))) / sum(power(sqrt((1.0 - p) / (p * eff)) / (-ln(p)), -{history_sharpen})) AS log_hc
  FROM e GROUP BY g
), c AS (
  SELECT s.g, s.filled, s.floor, {b} * ln({b} / greatest({b} - s.filled, {min_empty})) AS linear, ln({b} / greatest({b} - s.filled, {min_empty})) AS lam,
         exp(coalesce(t.log_lc, t.log_guard)) AS tiered_lc, exp(t.log_hc) AS history_raw,
         {K.MEAN_TERMINAL!r} * 2 * s.filled * s.filled / s0 * (s.filled + {b}) / (2 * {b}) AS mean_raw,
         {K.MEAN_HIST_TERMINAL!r} * 2 * s.filled * s.filled / s1 * (s.filled + {b}) / (2 * {b}) AS mean_hist_raw
  FROM s JOIN t ON t.g = s.g
), u AS (
  SELECT h.g, sum(n * {cubic}) AS state_sum, sum(n * {exact}) AS state_sum_exact
  FROM h JOIN c ON c.g = h.g GROUP BY h.g
), x AS (
  SELECT c.*, greatest(u.state_sum, c.filled) AS state_sum, greatest(u.state_sum_exact, c.filled) AS state_sum_exact,
         ln(c.tiered_lc / {b}) / ln(2.0) AS x0
  FROM c JOIN u ON u.g = c.g
), m AS (
  SELECT x.*, {m1} AS mean_one, {h1} AS mean_hist_one, history_raw * {_periodic('x0', K.HISTORY_CF)} AS history_count FROM x
), f AS (
  SELECT m.*, {m2.replace('one', 'mean_one')} AS mean, {h2.replace('one', 'mean_hist_one')} AS mean_hist,
         state_sum * (1.0 - {low_w}) + tiered_lc * {low_w} AS low_blend FROM m
), y AS (
  SELECT f.*, low_blend * (1.0 - {ramp_w}) + coalesce(history_count, low_blend) * {ramp_w} AS layered,
         state_sum * (1.0 - {harm_w}) + mean * {harm_w} AS harmonic0, state_sum * (1.0 - {harm_w}) + mean_hist * {harm_w} AS harmonic2 FROM f
)
SELECT g, CAST(filled AS BIGINT) AS filled, CAST(floor AS INT) AS floor, linear, tiered_lc, history_count, mean, mean_hist, state_sum, state_sum_exact,
       low_blend, layered, harmonic0, harmonic2, {1 - blend.mix} * layered + {blend.mix} * harmonic2 AS hybrid FROM y"""
