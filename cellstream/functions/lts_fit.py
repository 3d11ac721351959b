"""Fit of level-trend-season parameters by a bounded quasi-Newton method, and of first states by least squares, in numpy."""

from __future__ import annotations

import numpy as np


def start(y: np.ndarray, m: int) -> tuple[float, float, np.ndarray]:
    """Level and trend from season means (least squares over all whole seasons), season from their differences."""
    seasons = len(y) // m
    whole = y[: seasons * m].reshape(seasons, m)
    means = whole.mean(1)
    trend = (means[-1] - means[0]) / (m * (seasons - 1)) if seasons > 1 else 0.0
    season = (whole - means[:, None] - trend * (np.arange(m) - (m - 1) / 2)).mean(0)
    return means[0] - trend * ((m - 1) / 2 + 1), trend, season


def run(y: np.ndarray, m: int, p: np.ndarray, init) -> tuple[float, np.ndarray, tuple]:
    """SSE, its gradient in (alpha, beta, gamma) by forward sensitivities, and the last state."""
    a, b, g = p
    level, trend, season = init[0], init[1], init[2].copy()
    dl, db, ds = np.zeros(3), np.zeros(3), np.zeros((m, 3))
    sse, grad = 0.0, np.zeros(3)
    for t, v in enumerate(y):
        k = t % m
        old, dold, base, dbase = season[k], ds[k].copy(), level + trend, dl + db
        e = v - base - old
        de = -dbase - dold
        sse += e * e
        grad += 2 * e * de
        new = a * (v - old) + (1 - a) * base
        dnew = -a * dold + (1 - a) * dbase
        dnew[0] += v - old - base
        tnew = b * (new - level) + (1 - b) * trend
        dt = b * (dnew - dl) + (1 - b) * db
        dt[1] += new - level - trend
        season[k] = g * (v - base) + (1 - g) * old
        ds[k] = -g * dbase + (1 - g) * dold
        ds[k, 2] += v - base - old
        level, trend, dl, db = new, tnew, dnew, dt
    return sse, grad, (level, trend, season)


def fit(y: np.ndarray, m: int, init=None, starts=((0.3, 0.1, 0.1), (0.8, 0.05, 0.3), (0.1, 0.01, 0.5)), iterations: int = 60):
    """(params, sse, last state): projected BFGS from a few starts, the best kept."""
    init = init or start(y, m)
    best = None
    for p in starts:
        p = np.array(p, float)
        f, g, state = run(y, m, p, init)
        inverse = np.eye(3) / max(np.linalg.norm(g), 1e-12)
        for _ in range(iterations):
            free = ~(((p <= 0) & (g > 0)) | ((p >= 1) & (g < 0)))
            if not free.any() or np.linalg.norm(g[free]) < 1e-9 * max(1.0, f):
                break
            d = np.where(free, -(inverse @ np.where(free, g, 0)), 0)
            if d @ g >= 0:
                d, inverse = np.where(free, -g, 0) / max(np.linalg.norm(g), 1e-12), np.eye(3) / max(np.linalg.norm(g), 1e-12)
            step = 1.0
            while step > 1e-10:
                q = np.clip(p + step * d, 0, 1)
                fq, gq, sq = run(y, m, q, init)
                if np.isfinite(fq) and fq < f - 1e-10 * abs(f):
                    break
                step *= 0.4
            else:
                break
            s, r = q - p, gq - g
            if s @ r > 1e-14:
                rho = 1 / (s @ r)
                left = np.eye(3) - rho * np.outer(s, r)
                inverse = left @ inverse @ left.T + rho * np.outer(s, s)
            p, f, g, state = q, fq, gq, sq
        if best is None or f < best[1]:
            best = (p, f, state)
    return best


def first_states(y: np.ndarray, m: int, p: np.ndarray) -> tuple:
    """The first level, trend and season with the least squared error for given parameters.

    Errors are linear in the first states, so each step's error is a row of coefficients on (level, trend, seasons, 1).
    A constant may move between level and season; the solution of least norm around the usual start is taken.
    """
    a, b, g = p
    n = m + 3
    eye = np.eye(n)
    level, trend, season, one = eye[0], eye[1], eye[2 : 2 + m].copy(), eye[n - 1]
    errors = np.empty((len(y), n))
    for t, v in enumerate(y):
        k, base = t % m, level + trend
        old = season[k].copy()
        errors[t] = v * one - base - old
        new = a * (v * one - old) + (1 - a) * base
        trend = b * (new - level) + (1 - b) * trend
        season[k] = g * (v * one - base) + (1 - g) * old
        level = new
    usual = start(y, m)
    x = np.r_[usual[0], usual[1], usual[2]]
    x = x - np.linalg.lstsq(errors[:, :-1], errors[:, :-1] @ x + errors[:, -1], rcond=1e-10)[0]
    return float(x[0]), float(x[1]), x[2:]


def fit_states(y: np.ndarray, m: int, rounds: int = 4):
    """As fit, with first states estimated as well: parameters and first states in turn, while the error falls."""
    best, init = fit(y, m), start(y, m)
    for _ in range(rounds):
        init = first_states(y, m, best[0])
        now = fit(y, m, init, starts=(tuple(best[0]), (0.3, 0.1, 0.1)))
        if not now[1] < best[1] * (1 - 1e-9):
            break
        best = now
    return best
