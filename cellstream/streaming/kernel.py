"""One step of the online update, in numpy: state and a slice's observed cells in, state and outputs out."""

from __future__ import annotations

import numpy as np

from ..model import HyperParams, SeasonState, Snapshot


class Diverged(RuntimeError):
    pass


def psi(x, k):
    return np.clip(x, -k, k)


def rho(x, k, c):
    return np.where(np.abs(x) <= k, c * (1 - (1 - (x / k) ** 2) ** 3), c)


def predict_time(state: Snapshot) -> np.ndarray:
    s = state.season
    return s.level + s.trend + s.season[(state.t + 1) % len(s.season)]


def rows(factors: list[np.ndarray], idx: np.ndarray, skip: int | None = None) -> np.ndarray:
    p = np.ones((len(idx), factors[0].shape[1]))
    for n, u in enumerate(factors):
        if n != skip:
            p = p * u[idx[:, n]]
    return p


def scattered(at: np.ndarray, values: np.ndarray, size: int) -> np.ndarray:
    """Sums of rows of values by index."""
    return np.stack([np.bincount(at, values[:, j], minlength=size) for j in range(values.shape[1])], 1)


def update_season(s: SeasonState, w: np.ndarray, slot: int) -> SeasonState:
    old, base = s.season[slot], s.level + s.trend
    level = s.alpha * (w - old) + (1 - s.alpha) * base
    trend = s.beta * (level - s.level) + (1 - s.beta) * s.trend
    season = s.season.copy()
    season[slot] = s.gamma * (w - base) + (1 - s.gamma) * old
    return SeasonState(level, trend, season, s.alpha, s.beta, s.gamma)


def advance(state: Snapshot, idx: np.ndarray, y: np.ndarray, hp: HyperParams, in_place: bool = False) -> tuple[Snapshot, dict]:
    """The state after step state.t + 1, and what the step found: y_hat, outlier and squared scale of each cell.

    idx: cells x modes. A step without cells has only the pulls to earlier time vectors and the season update.
    All gradients are taken at the old factors. Work is in proportion to the cells.
    """
    m, t = len(state.ring), state.t + 1
    slot = t % m
    w_hat = predict_time(state)
    before, season_ago = state.ring[state.t % m], state.ring[slot]
    factors = state.factors
    p = rows(factors, idx)
    y_hat = p @ w_hat
    start = (hp.lambda3 * hp.floor) ** 2
    sigma2 = state.scales.get(idx, start)
    sigma = np.sqrt(sigma2)
    z = (y - y_hat) / sigma
    r = psi(z, hp.k) * sigma
    outlier = y - y_hat - r
    sigma2 = sigma2 * (1 - hp.phi + hp.phi * rho(z, hp.k, hp.c_k))
    scales = state.scales if in_place else state.scales.copy()
    scales.put(idx, sigma2)
    scaled = hp.step_rule == "row_scaled"
    new = []
    for n, u in enumerate(factors):
        h = rows(factors, idx, n) * w_hat
        g = scattered(idx[:, n], r[:, None] * h, len(u))
        if scaled:
            size = np.bincount(idx[:, n], (h * h).sum(1), minlength=len(u))
            g = g / np.where(size > 0, size, 1.0)[:, None]
        new.append(u + 2 * hp.mu * g)
    pull = r @ p + hp.lambda1 * (before - w_hat) + hp.lambda2 * (season_ago - w_hat)
    if scaled:
        pull = pull / max((p * p).sum() + hp.lambda1 + hp.lambda2, 1e-300)
    w = w_hat + 2 * hp.mu * pull
    new, w = finished(new, w, t, hp)
    ring = state.ring.copy()
    ring[slot] = w
    out = {"y_hat": y_hat, "outlier": outlier, "sigma2": sigma2, "w": w, "w_hat": w_hat}
    return Snapshot(new, update_season(state.season, w, slot), ring, t, scales), out


def finished(factors: list[np.ndarray], w: np.ndarray, t: int, hp: HyperParams) -> tuple[list[np.ndarray], np.ndarray]:
    """A step's factors and time vector, renormalized where that is asked for, and held against divergence."""
    if hp.renormalize:
        factors = list(factors)
        for n, u in enumerate(factors):
            norms = np.where((x := np.linalg.norm(u, axis=0)) > 0, x, 1.0)
            factors[n] = u / norms
            w = w * norms
    if not np.isfinite(w).all() or np.abs(w).max(initial=0) > 1e12:
        raise Diverged(f"step {t}: the time vector left all bounds; use step_rule='row_scaled' or a smaller mu")
    return factors, w


def impute(state: Snapshot, idx: np.ndarray) -> np.ndarray:
    """Values at any coordinates of the last step, with its new factors."""
    return rows(state.factors, idx) @ state.ring[state.t % len(state.ring)]


def forecast_time(state: Snapshot, h: int) -> np.ndarray:
    s, m = state.season, len(state.ring)
    return s.level + h * s.trend + s.season[(state.t + 1 + (h - 1) % m) % m]


def forecast(state: Snapshot, idx: np.ndarray, h: int) -> np.ndarray:
    return rows(state.factors, idx) @ forecast_time(state, h)
