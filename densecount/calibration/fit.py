"""Derive the estimators' constants; ``python -m densecount.calibration.fit`` prints them.

Nothing is simulated. A register at load lam (elements per register) has seen level k with
probability 1 - exp(-lam / 2**(k+1)), independently. From that follow: the weights of the
history cells (least variance of the harmonic sum over an octave), the correction curves
(true load over the raw estimator on the expected histogram), and the expected elements per
register state, to which cubics in the load are fitted. The correction curves are fitted by
three sigmoids and two Gaussians in log2(load), by damped least squares.
"""

from __future__ import annotations

import numpy as np

LEVELS = 64
K = np.arange(LEVELS)


def seen(lam: float) -> np.ndarray:
    return -np.expm1(-lam * 2.0 ** -(K + 1))


def expected_histogram(lam: float) -> np.ndarray:
    """Share of registers by (highest rank, two-bit history); levels below 0 count as seen."""
    q = seen(lam)
    above = np.concatenate([np.cumprod((1 - q)[::-1])[::-1][1:], [1.0]])
    top = q * above
    one, two = np.concatenate([[1.0], q[:-1]]), np.concatenate([[1.0, 1.0], q[:-2]])
    return np.stack([top * (1 - one) * (1 - two), top * (1 - one) * two, top * one * (1 - two), top * one * two], 1)


def history_weights() -> np.ndarray:
    """Weights of histories 0..3 (3: 1.0) that minimise the variance of sum w * 2**-z."""
    first, second = np.zeros(4), np.zeros(4)
    for lam in 2.0 ** np.linspace(20, 21, 65)[:-1]:
        p = expected_histogram(lam)
        y = lam * 2.0**-K
        first += (p * y[:, None]).sum(0)
        second += (p * y[:, None] ** 2).sum(0)
    w = first / second
    return w / w[3]


def raw_mean(p: np.ndarray, w: np.ndarray, terminal: float) -> float:
    """Harmonic estimator over B registers, divided by B."""
    filled = p.sum()
    return terminal * 2 * filled * filled / (p @ w * 2.0**-K).sum() * (filled + 1) / 2


def curve(w: np.ndarray, terminal: float, xs: np.ndarray) -> np.ndarray:
    return np.array([2.0**x / raw_mean(expected_histogram(2.0**x), w, terminal) for x in xs])


def terminal_factor(w: np.ndarray) -> float:
    xs = np.linspace(16, 17, 33)[:-1]
    return float(np.exp(np.mean(np.log(curve(w, 1.0, xs)))))


def sigmoid_gauss(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    y = np.full_like(x, c[0])
    for i in range(3):
        y = y + c[1 + 3 * i] * np.tanh((x - c[2 + 3 * i]) / c[3 + 3 * i])
    for i in range(2):
        y = y + c[10 + 3 * i] * np.exp(-(((x - c[11 + 3 * i]) / c[12 + 3 * i]) ** 2))
    return y


def least_squares(f, c: np.ndarray, x: np.ndarray, y: np.ndarray, steps: int = 400) -> np.ndarray:
    """Damped Gauss-Newton with numeric derivatives."""
    damp = 1e-2
    error = ((f(x, c) - y) ** 2).sum()
    for _ in range(steps):
        jac = np.stack([(f(x, c + h) - f(x, c - h)) / 2e-6 for h in np.eye(len(c)) * 1e-6], 1)
        a, g = jac.T @ jac, jac.T @ (y - f(x, c))
        new = c + np.linalg.solve(a + damp * np.diag(np.diag(a) + 1e-9), g)
        trial = ((f(x, new) - y) ** 2).sum()
        if np.isfinite(trial) and trial < error:
            c, error, damp = new, trial, max(damp / 3, 1e-12)
        else:
            damp *= 4
            if damp > 1e12:
                break
    return c


def r_squared(y: np.ndarray, fitted: np.ndarray) -> float:
    return 1 - ((y - fitted) ** 2).sum() / ((y - y.mean()) ** 2).sum()


def fit_curve(w: np.ndarray, terminal: float) -> tuple[np.ndarray, float]:
    xs = np.linspace(-8, 13, 421)
    ys = curve(w, terminal, xs)
    best, rng = None, np.random.default_rng(1)
    for _ in range(24):
        start = np.concatenate([[1.0], *[[rng.normal(0, 0.2), rng.uniform(-5, 5), rng.uniform(0.5, 3)] for _ in range(5)]])
        try:
            c = least_squares(sigmoid_gauss, start, xs, ys)
        except np.linalg.LinAlgError:
            continue
        r = r_squared(ys, sigmoid_gauss(xs, c))
        if best is None or r > best[1]:
            best = (c, r)
    return best


def elements(lam: float, z: int, high: int, low: int) -> float:
    """Expected elements in a register of a given state at load lam."""

    def given(k: int) -> float:
        mu = lam * 2.0 ** -(k + 1)
        return mu / -np.expm1(-mu)

    total = given(z) + (given(z - 1) if z >= 1 and high else 0) + (given(z - 2) if z >= 2 and low else 0)
    return total + (lam * (1 - 2.0 ** -(z - 2)) if z >= 3 else 0)


#: state index: 0 empty, 1 rank 0, 2-3 rank 1 by the high bit, 4-7 rank 2, 8-11 ranks from 3
def state_polynomials() -> tuple[list[list[float]], float]:
    lams = np.linspace(0.02, 7, 140)
    out, worst = [], 1.0
    for state in range(1, 12):
        ys = []
        for lam in lams:
            if state == 1:
                ys.append(elements(lam, 0, 0, 0))
            elif state < 4:
                ys.append(elements(lam, 1, state - 2, 0))
            elif state < 8:
                ys.append(elements(lam, 2, (state - 4) // 2, (state - 4) % 2))
            else:
                h = state - 8
                p = expected_histogram(lam)[3:, h] + 1e-300
                ys.append(float(np.sum([p[i] * elements(lam, 3 + i, h // 2, h % 2) for i in range(40)]) / p[:40].sum()))
        c = np.polyfit(lams, ys, 3)
        worst = min(worst, r_squared(np.array(ys), np.polyval(c, lams)))
        out.append([float(x) for x in c[::-1]])
    return out, worst


def history_curve(xs: np.ndarray) -> np.ndarray:
    """True load over the history estimator on the expected histogram."""
    out = []
    for x in xs:
        lam = 2.0**x
        p = expected_histogram(lam) * 1408
        total = weight = 0.0
        for t in range(LEVELS - 2):
            near = p[t + 1] if t + 1 < LEVELS else np.zeros(4)
            far = p[t + 2]
            eff, unseen = near.sum() + far.sum(), near[0] + near[1] + far[0] + far[2]
            if eff >= 8 and 1 <= unseen < eff:
                share = unseen / eff
                w = share * eff * np.log(share) ** 2 / (1 - share)
                total += w * np.log(2.0 ** (t + 1) * -np.log(share))
                weight += w
        out.append(lam / np.exp(total / weight) if weight else 1.0)
    return np.array(out)


def periodic(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    wave = 2 * np.pi * x
    return c[0] - c[1] * np.exp(-c[2] * x) + (c[3] + c[4] * x) * np.sin(wave) + (c[5] + c[6] * x) * np.cos(wave)


def main() -> None:
    w = history_weights()
    t0, t3 = terminal_factor(np.ones(4)), terminal_factor(w)
    print("HISTORY_WEIGHTS =", [round(float(x), 6) for x in w])
    print("MEAN_TERMINAL =", round(t0, 6))
    print("MEAN_HIST_TERMINAL =", round(t3, 6))
    for name, weights, terminal in (("MEAN_CF", np.ones(4), t0), ("MEAN_HIST_CF", w, t3)):
        c, r = fit_curve(weights, terminal)
        print(f"{name} = {[round(float(x), 8) for x in c]}  # R2 {r:.6f}")
    polys, r = state_polynomials()
    print("STATE_POLYNOMIALS = [" + ",\n    ".join(str([round(x, 8) for x in p]) for p in polys) + f"]  # least R2 {r:.6f}")
    xs = np.linspace(1, 13, 241)
    ys = history_curve(xs)
    c = least_squares(periodic, np.array([1.0, 0.01, 0.5, 0, 0, 0, 0]), xs, ys)
    print(f"HISTORY_CF = {[round(float(x), 8) for x in c]}  # R2 {r_squared(ys, periodic(xs, c)):.4f}, curve {ys.min():.4f}..{ys.max():.4f}")


if __name__ == "__main__":
    main()
