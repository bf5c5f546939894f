"""Estimates of many sketches at once, from histograms as a tensor [sketch, rank, history].

The arithmetic is that of ``plans.estimate``, written for NumPy: the SQL text is its oracle,
so the two are checked against each other wherever an estimate is compared.
"""

from __future__ import annotations

import numpy as np

from ..calibration import constants as K
from ..calibration.fit import sigmoid_gauss
from ..plans.estimate import BlendSpec

RANKS = 64
LN2 = np.log(2.0)


def _weighted(logs: np.ndarray, errors: np.ndarray, ok: np.ndarray, sharpen: float) -> np.ndarray:
    """Mean of logs by error to the power of -sharpen; NaN where nothing is valid."""
    w = np.where(ok, np.where(ok, errors, 1.0) ** -sharpen, 0.0)
    with np.errstate(invalid="ignore"):
        return (w * np.where(ok, logs, 0.0)).sum(1) / w.sum(1)


def _periodic(x: np.ndarray, c: tuple[float, ...]) -> np.ndarray:
    return c[0] - c[1] * np.exp(-c[2] * x) + (c[3] + c[4] * x) * np.sin(2 * np.pi * x) + (c[5] + c[6] * x) * np.cos(2 * np.pi * x)


def _ramp(x: np.ndarray, b: np.ndarray, lo: float, hi: float) -> np.ndarray:
    return np.clip(np.log(np.maximum(x, 1e-9) / (lo * b)) / np.log(hi / lo), 0, 1)


def components(cells: np.ndarray, registers, blend: BlendSpec = BlendSpec(), sharpen: float = 4.5, min_empty: float = 0.5, history_sharpen: float = 2.0, polynomials: tuple = K.STATE_POLYNOMIALS) -> dict[str, np.ndarray]:
    """filled, floor and every estimator of ``cells`` (counts [sketch, rank, history]) with so
    many ``registers`` (one number, or one for each). Every sketch has a filled register."""
    h = np.asarray(cells, float)
    b = np.broadcast_to(np.asarray(registers, float), len(h))
    n = h.sum(2)
    some = n > 0
    filled, lo, hi = n.sum(1), some.argmax(1), n.shape[1] - 1 - some[:, ::-1].argmax(1)
    floor = np.where(filled < b, -1, np.maximum(-1, lo - 2))
    k = np.arange(RANKS - 1)
    here = (k >= np.maximum(0, lo - 2)[:, None]) & (k <= hi[:, None] + 1)
    bc = b[:, None]

    # tiers: registers that saw nothing from rank k on
    empty = bc - np.cumsum(n[:, ::-1], 1)[:, ::-1][:, : RANKS - 1]
    ok = here & (empty >= 1) & (empty <= bc - 1)
    lam = np.log(bc / np.where(ok, empty, bc / 2))
    log_lc = _weighted(k * LN2 + np.log(bc) + np.log(lam), np.sqrt(np.exp(lam) - 1) / (lam * np.sqrt(bc)), ok, sharpen)
    guard = hi * LN2 + np.log(b) + np.log(np.log(b / min_empty))
    tiered = np.exp(np.where(np.isnan(log_lc), guard, log_lc))

    # history bits of rank k in registers one and two ranks above
    z = np.arange(RANKS)
    kept = np.where((z - floor[:, None] <= 13)[:, :, None], h, 0.0)
    wide = np.concatenate([kept, np.zeros((len(h), 2, 4))], 1)
    one, two = wide[:, 1:RANKS], wide[:, 2 : RANKS + 1]
    eff = one.sum(2) + two.sum(2)
    unseen = one[:, :, :2].sum(2) + two[:, :, [0, 2]].sum(2)
    ok = here & (eff >= 8) & (unseen >= 1) & (unseen < eff)
    p = np.where(ok, unseen / np.where(ok, eff, 1.0), 0.5)
    log_hc = _weighted((k + 1) * LN2 + np.log(bc) + np.log(-np.log(p)), np.sqrt((1 - p) / (p * np.where(ok, eff, 1.0))) / -np.log(p), ok, history_sharpen)
    x0 = np.log(tiered / b) / LN2
    history = np.exp(log_hc) * _periodic(x0, K.HISTORY_CF)

    # harmonic means, corrected at the reference estimate and, high up, once more
    full = np.arange(4)[None, :].repeat(RANKS, 0)
    full[0], full[1] = 3, np.arange(4) | 1
    area = 2.0**-z
    s0, s1 = (n * area).sum(1), (h * area[:, None] * np.array(K.HISTORY_WEIGHTS)[full]).sum((1, 2))
    shape = 2 * filled * filled * (filled + b) / (2 * b)

    def corrected(raw: np.ndarray, cf: tuple[float, ...]) -> np.ndarray:
        first = raw * sigmoid_gauss(x0, np.array(cf))
        again = raw * sigmoid_gauss(np.log(np.maximum(first, 1e-9) / b) / LN2, np.array(cf))
        return np.where(tiered > 10 * b, again, first)

    mean, mean_hist = corrected(K.MEAN_TERMINAL * shape / s0, K.MEAN_CF), corrected(K.MEAN_HIST_TERMINAL * shape / s1, K.MEAN_HIST_CF)

    # elements expected in a register of each state, at the load the empty ones tell
    load = np.log(b / np.maximum(b - filled, min_empty))
    states = np.array([[0] * 4, [1, 1, 2, 2], [3, 4, 5, 6]] + [[7, 8, 9, 10]] * (RANKS - 3))
    c = np.array(polynomials)[states]
    powers = load[:, None] ** np.arange(4)
    state_sum = np.maximum(np.einsum("gzh,zhi,gi->g", h, c, powers, optimize=True), filled)
    mu = load[:, None] * 2.0 ** (-z - 1.0)
    seen = mu / -np.expm1(-mu)
    before, second = np.concatenate([np.zeros((len(h), 1)), seen[:, :-1]], 1), np.concatenate([np.zeros((len(h), 2)), seen[:, :-2]], 1)
    below = np.where(z >= 3, load[:, None] * (1 - 2.0 ** np.minimum(2.0 - z, 0)), 0.0)
    each = (seen + below)[:, :, None] + before[:, :, None] * (np.arange(4) >= 2) + second[:, :, None] * (np.arange(4) % 2)
    exact = np.maximum((h * each).sum((1, 2)), filled)

    w = _ramp(tiered, b, *blend.low)
    low = state_sum * (1 - w) + tiered * w
    (r0, r1, rw), a = blend.ramp, _ramp(tiered, b, *blend.harmonic)
    w = rw * np.clip((low / b - r0) / (r1 - r0), 0, 1)
    layered = low * (1 - w) + np.where(np.isnan(history), low, history) * w
    harmonic0, harmonic2 = state_sum * (1 - a) + mean * a, state_sum * (1 - a) + mean_hist * a
    return {
        "filled": filled, "floor": floor, "linear": b * load, "tiered_lc": tiered, "history_count": history, "mean": mean, "mean_hist": mean_hist, "state_sum": state_sum, "state_sum_exact": exact,
        "low_blend": low, "layered": layered, "harmonic0": harmonic0, "harmonic2": harmonic2, "hybrid": (1 - blend.mix) * layered + blend.mix * harmonic2,
    }


def dense_ml(cells: np.ndarray, registers) -> np.ndarray:
    """Maximum likelihood of highest ranks and two history bits, by halving the log load.

    The score of a level that was seen is mu / (e**mu - 1), that of one that was not is -mu;
    levels above a register's highest were not seen, those below its window say nothing."""
    h = np.asarray(cells, float)
    b = np.broadcast_to(np.asarray(registers, float), len(h))
    z, hist = np.arange(RANKS)[:, None], np.arange(4)[None, :]
    rate = lambda k: np.where(k >= 0, 2.0 ** (-k - 1.0), 0.0)
    unseen = rate(z) + np.where(hist >= 2, 0, rate(z - 1)) + np.where(hist % 2 == 1, 0, rate(z - 2))
    alpha = (h * unseen).sum((1, 2)) + b - h.sum((1, 2))
    beta = np.zeros((len(h), RANKS))  # registers known to have seen each level
    beta += h.sum(2)
    beta[:, :-1] += h[:, 1:, 2:].sum(2)
    beta[:, :-2] += h[:, 2:, 1::2].sum(2)
    lo, hi = np.full(len(h), -20.0), np.full(len(h), 50.0)
    level = rate(np.arange(RANKS))
    for _ in range(56):
        mid = (lo + hi) / 2
        mu = (2.0**mid)[:, None] * level
        above = (beta * level / np.expm1(np.minimum(mu, 700.0))).sum(1) > alpha
        lo, hi = np.where(above, mid, lo), np.where(above, hi, mid)
    return b * 2.0 ** ((lo + hi) / 2)


def histogram(z: np.ndarray, history: np.ndarray) -> np.ndarray:
    """Counts [rank, history] of registers; rank -1 is empty and not counted."""
    some = z >= 0
    return np.bincount(z[some] * 4 + history[some], minlength=RANKS * 4).reshape(RANKS, 4)
