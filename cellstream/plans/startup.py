"""Start-up: alternate smooth least squares and soft-thresholded outliers, then fit the seasons of the time factor."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import lts_fit
from ..model import HyperParams, SeasonState, Snapshot, TensorSpec
from . import smooth_als


def soft(x: np.ndarray, threshold: float) -> np.ndarray:
    return np.sign(x) * np.maximum(np.abs(x) - threshold, 0)


def run_local(idx: np.ndarray, y: np.ndarray, spec: TensorSpec, hp: HyperParams, steps: int, solver: str = "smooth", trace: list | None = None, seed: int | None = None) -> tuple[list[np.ndarray], np.ndarray]:
    """(factors, outliers of the cells): cells idx (n x modes + time), y of the first `steps` steps."""
    if solver == "plain":
        hp = hp.with_(lambda1=0.0, lambda2=0.0)
    factors = smooth_als.initial_factors((*spec.sizes, steps), spec.rank, hp.seed if seed is None else seed, hp.dist)
    o, threshold, old = np.zeros(len(y)), hp.lambda3, None
    for _ in range(hp.max_iter):
        smooth_als.fit_local(factors, idx, y - o, spec.period, hp)
        o = soft(y - smooth_als.products(factors, idx).sum(1), threshold / (2 if hp.half_threshold else 1))
        threshold = max(hp.decay * threshold, hp.lambda3 * hp.floor)
        if trace is not None:
            trace.append([u.copy() for u in factors])
        if old is not None and smooth_als.relative_change(factors, old) < hp.tol:
            break
        old = [u.copy() for u in factors]
    return factors, o


def run(cells: DataFrame, spec: TensorSpec, hp: HyperParams, solver: str = "smooth") -> list[np.ndarray]:
    """As run_local, over a DataFrame of start-up cells: outliers are a function of the cell's residual, so the pass
    that sums a mode's row systems takes them off with the factors and threshold before it; cells stay as they are."""
    if solver == "plain":
        hp = hp.with_(lambda1=0.0, lambda2=0.0)
    names = [*spec.modes, "t"]
    cells = cells.where(F.col("t") < spec.startup).select(*names, "y").persist()
    try:
        factors = smooth_als.initial_factors((*spec.sizes, spec.startup), spec.rank, hp.seed, hp.dist)
        outliers, threshold, old = None, hp.lambda3, None
        for _ in range(hp.max_iter):
            smooth_als.fit_distributed(cells, factors, spec, hp, outliers)
            frozen = [u.copy() for u in factors]
            outliers = frozen, threshold / (2 if hp.half_threshold else 1)
            threshold = max(hp.decay * threshold, hp.lambda3 * hp.floor)
            if old is not None and smooth_als.relative_change(factors, old) < hp.tol:
                break
            old = frozen
        return factors
    finally:
        cells.unpersist()


def best(cells: DataFrame, spec: TensorSpec, hp: HyperParams, starts: int = 3, solver: str = "smooth") -> list[np.ndarray]:
    """As best_local, over a DataFrame: of several random starts, the factors with the least mean absolute residual."""
    if starts == 1:
        return run(cells, spec, hp, solver)
    names, found = [*spec.modes, "t"], None
    early = cells.where(F.col("t") < spec.startup)
    for k in range(starts):
        factors = run(cells, spec, hp.with_(seed=hp.seed + 101 * k), solver)
        loss = smooth_als.residuals(early.select(*names, "y"), factors, names).agg(F.avg(F.abs(F.col("y") - F.col("x_hat")))).first()[0]
        if found is None or loss < found[0]:
            found = loss, factors
    return found[1]


def fit_seasons(w: np.ndarray, m: int, states: bool = False) -> SeasonState:
    """Parameters and last states of every column of the time factor; states: first states are estimated too."""
    steps, rank = w.shape
    out = [(lts_fit.fit_states if states else lts_fit.fit)(w[:, r], m) for r in range(rank)]
    level, trend = (np.array([o[2][k] for o in out]) for k in (0, 1))
    season = np.stack([o[2][2] for o in out], 1)  # slot t mod m
    p = np.array([o[0] for o in out])
    return SeasonState(level, trend, season, p[:, 0], p[:, 1], p[:, 2])


def snapshot(factors: list[np.ndarray], spec: TensorSpec) -> Snapshot:
    """The state after the start-up: the time rows' last season and the fitted seasons."""
    w, m = factors[-1], spec.period
    if len(w) < m:
        raise ValueError(f"a start-up of {len(w)} steps is shorter than a season of {m}")
    ring = np.empty((m, spec.rank))
    for t in range(len(w) - m, len(w)):
        ring[t % m] = w[t]
    return Snapshot([u.copy() for u in factors[:-1]], fit_seasons(w, m), ring, len(w) - 1)


def best_local(idx: np.ndarray, y: np.ndarray, spec: TensorSpec, hp: HyperParams, steps: int, starts: int = 3, solver: str = "smooth"):
    """Of several random starts, the one with the least absolute residual (outliers weigh little in it)."""
    best = None
    for k in range(starts):
        factors, o = run_local(idx, y, spec, hp, steps, solver, seed=hp.seed + 101 * k)
        loss = np.abs(y - smooth_als.products(factors, idx).sum(1)).mean()
        if best is None or loss < best[0]:
            best = loss, factors, o
    return best[1], best[2]
