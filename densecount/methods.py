"""Every method's register encoding and estimate for one simulated sketch, in NumPy.

A method reads ``first``, the element number at which each (register, level) is first seen,
keeps what its encoding can hold at a checkpoint, and estimates from that alone.
"""

from __future__ import annotations

import numpy as np

from . import baselines
from .functions import codec
from .operators import tensor

LEVELS = 44


def first_seen(rng: np.random.Generator, registers: int, split: int = 1, exact: int = 32_768, begun: np.ndarray | None = None, n: int = 0) -> np.ndarray:
    """[register, level * split + part]: the first ``exact`` elements are drawn one by one,
    later first arrivals by exponential times, of which only the tails are needed. ``begun``
    are first arrivals among ``n`` given elements, after which the drawn ones follow."""
    rate = np.repeat(2.0 ** -(np.arange(LEVELS) + 1.0) / (split * registers), split)
    t = np.full(registers * LEVELS * split, np.inf)
    if n < exact:
        bucket = rng.integers(registers, size=exact - n)
        level = np.minimum(-np.log2(1 - rng.random(exact - n)), LEVELS - 1).astype(np.int64)
        cell = bucket * (LEVELS * split) + level * split + (rng.integers(split, size=exact - n) if split > 1 else 0)
        t[cell[::-1]] = np.arange(exact, n, -1)  # the earliest of a cell is assigned last
    if begun is not None:
        t = np.minimum(t, begun)
    late = np.isinf(t)
    t[late] = max(exact, n) + rng.exponential(1.0, int(late.sum())) / np.tile(rate, registers)[late]
    return t.reshape(registers, LEVELS * split)


def note(begun: np.ndarray, h: np.ndarray, z: np.ndarray, place: np.ndarray, registers: int, split: int = 1) -> None:
    """Lower ``begun`` to the places of elements with hashes ``h`` and ranks ``z``; places rise."""
    low = (h >> np.uint64(baselines.LOW_SHIFT)).astype(np.int64) % split if split > 1 else 0
    bucket = (h - h // np.uint64(registers) * np.uint64(registers)).astype(np.int64)
    cell = (bucket * LEVELS + np.minimum(z, LEVELS - 1)) * split + low
    new = np.flatnonzero(begun[cell] > place)[::-1]
    begun[cell[new]] = place[new]  # the earliest of a cell is assigned last


def levels(first: np.ndarray, at: float) -> tuple[np.ndarray, np.ndarray]:
    """(highest level or -1, two-bit history) of each register."""
    seen = first <= at
    top = np.where(seen.any(1), seen.shape[1] - 1 - seen[:, ::-1].argmax(1), -1)
    row = np.arange(len(top))
    one, two = seen[row, np.maximum(top - 1, 0)] & (top >= 1), seen[row, np.maximum(top - 2, 0)] & (top >= 2)
    return top, 2 * one + two


def floor_of(top: np.ndarray) -> int:
    return max(-1, int(top.min()) - codec.MARGIN)


def dense56(first: np.ndarray, at: float) -> np.ndarray:
    """Histogram of the 56 states: exponents above 18 saturate, above 13 have no history."""
    top, history = levels(first, at)
    floor = floor_of(top)
    states = codec.states_np(np.where(top < 0, 0, top - floor), history)
    r = codec.EXPONENT[states]
    return tensor.histogram(np.where(r > 0, r + floor, -1), codec.HISTORY[states])


def shared_floor(first: np.ndarray, at: float, history_bits: bool) -> np.ndarray:
    """Histogram of 4-bit exponents above a shared floor, with or without two history bits."""
    top, history = levels(first, at)
    floor = floor_of(top) if history_bits else max(-1, int(top.min()) - 1)
    r = np.minimum(np.where(top < 0, 0, top - floor), 15)
    return tensor.histogram(np.where(r > 0, r + floor, -1), history if history_bits else np.zeros_like(history))


def max_only(name: str, top: np.ndarray) -> tuple[np.ndarray, int]:
    """Ranks an encoding gives back and the entries it keeps outside the registers."""
    base = int(top.min())
    if name == "tailcut4":
        return base + np.minimum(top - base, 15), 0
    if name == "offset3":  # the last of eight codes says that the map has the rank
        return top, int((top - base >= 7).sum())
    if name == "nibble4":
        return top, int((top + 1 >= 15).sum())
    return np.minimum(top, 62), 0


def hll(top: np.ndarray) -> float:
    b = len(top)
    raw = 0.7213 / (1 + 1.079 / b) * b * b / (2.0 ** -(top + 1.0)).sum()
    empty = int((top < 0).sum())
    return b * np.log(b / empty) if empty and raw <= 2.5 * b else raw


def byte_hist(first: np.ndarray, at: float) -> float:
    tau, eta, factor = baselines.history_eta()
    top, history = levels(first, at)
    b, filled = len(top), int((top >= 0).sum())
    linear = b * np.log(b / (b - filled)) if filled < b else np.inf
    if linear < 3 * b:
        return linear
    whole = np.where(top <= 0, 3, np.where(top == 1, history | 1, history))  # levels below 0 count as seen
    return factor * b * (np.array(eta)[whole] * 2.0 ** (-tau * top)).mean() ** (-1 / tau)


#: a threshold stands until fewer than one register in so many is empty
TWOBIT_FULL = 80


def twobit(rng: np.random.Generator, first: np.ndarray, marks: np.ndarray, repeats: bool) -> np.ndarray:
    """Estimates at all marks: two bit planes tell levels from the threshold, four above and
    eight above; the threshold starts at 1 and rises by 4. What is more than eight levels up
    is forgotten when the threshold has risen, unless elements come again."""
    b = len(first)
    out, begun = np.zeros(len(marks)), {1: 0.0}
    step = 1
    while step < LEVELS:
        seen = first[:, step:].min(1)
        known = begun.get(step - 8, 0.0)  # from when on these levels could be told
        lost = seen < known
        if lost.any() and not repeats:
            seen[lost] = known + rng.exponential(b * 2.0**step, int(lost.sum()))
        ends = np.partition(seen, b - b // TWOBIT_FULL)[b - b // TWOBIT_FULL]
        for i in np.flatnonzero((marks >= begun[step]) & (marks < ends)):
            out[i] = 2.0**step * b * np.log(b / max((seen > marks[i]).sum(), 0.5))
        begun[step + 4] = max(ends, begun[step])
        step += 4
    return out


def wide_ml(first: np.ndarray, at: float, t: int = 2, d: int = 24) -> float:
    """Maximum likelihood of a highest update value and the d values under it."""
    q, b = 1 << t, len(first)
    p = np.repeat(2.0 ** -(np.arange(LEVELS) + 1.0) / q, q)
    seen = first <= at
    top = np.where(seen.any(1), seen.shape[1] - 1 - seen[:, ::-1].argmax(1), -1)
    v = np.arange(len(p))
    known = (v <= top[:, None]) & (v >= top[:, None] - d) & (top[:, None] >= 0)
    alpha = (np.cumsum(p[::-1])[::-1][np.minimum(top + 1, len(p) - 1)] + 2.0**-LEVELS).sum() + (p * (known & ~seen)).sum()
    beta = (known & seen).sum(0)
    some = np.flatnonzero(beta)
    lo, hi = -20.0, 50.0
    for _ in range(50):
        x = 2.0 ** ((lo + hi) / 2)
        above = (beta[some] * p[some] / np.expm1(np.minimum(x * p[some], 700.0))).sum() > alpha
        lo, hi = ((lo + hi) / 2, hi) if above else (lo, (lo + hi) / 2)
    return b * 2.0 ** ((lo + hi) / 2)


def martingale(first: np.ndarray, marks: np.ndarray, t: int = 2, d: int = 24) -> np.ndarray:
    """Running estimates of the wide register at all marks: every change adds one over the
    chance that an element would have made a change. ``first`` is the time of the first arrival
    of each (register, update value). Depends on the order, so it can't be merged."""
    q, (b, width) = 1 << t, first.shape
    p = np.repeat(2.0 ** -(np.arange(width // q) + 1.0) / q, q)
    tail = np.append(np.cumsum(p[::-1])[::-1], 0.0)
    order = np.argsort(first, axis=None)
    order = order[first.ravel()[order] <= marks[-1]]
    top, share, seen = np.full(b, -1), np.ones(b), np.zeros(first.shape, bool)
    total, estimate, out, at = float(b), 0.0, np.zeros(len(marks)), 0
    for cell, when in zip(order.tolist(), first.ravel()[order].tolist()):
        while marks[at] < when:
            out[at], at = estimate, at + 1
        r, v = divmod(cell, width)
        if v < top[r] - d:
            continue
        estimate += b / total
        seen[r, v] = True
        top[r] = max(top[r], v)
        low = max(0, top[r] - d)
        new = tail[top[r] + 1] + (p[low : top[r]] * ~seen[r, low : top[r]]).sum()
        total += new - share[r]
        share[r] = new
    out[at:] = estimate
    return out
