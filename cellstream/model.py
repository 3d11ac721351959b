"""What a stream is, its parameters, and the state between two steps."""

from __future__ import annotations

from dataclasses import asdict, dataclass

import numpy as np


@dataclass(frozen=True)
class TensorSpec:
    """A stream of slices: sizes of the non-temporal modes, period, rank and the number of start-up seasons."""

    sizes: tuple[int, ...]
    period: int
    rank: int
    seasons: int = 3

    @property
    def modes(self) -> list[str]:
        return [f"i{n + 1}" for n in range(len(self.sizes))]

    @property
    def startup(self) -> int:
        return self.period * self.seasons


@dataclass(frozen=True)
class HyperParams:
    """Defaults are the published ones, but for step_rule: the fixed step diverges unless data are scaled for it."""

    lambda1: float = 1e-3
    lambda2: float = 1e-3
    lambda3: float = 10.0
    mu: float = 0.1
    phi: float = 0.01
    decay: float = 0.85
    floor: float = 0.01
    k: float = 2.0
    c_k: float = 2.52
    max_iter: int = 300
    inner_max_iter: int = 1
    tol: float = 1e-4
    step_rule: str = "row_scaled"
    time_order: str = "gauss_seidel"
    renormalize: bool = False
    half_threshold: bool = False
    seed: int = 7
    dist: str = "uniform"

    def with_(self, **changes) -> HyperParams:
        return HyperParams(**{**asdict(self), **changes})


@dataclass
class SeasonState:
    """Level, trend and the last season of each component; slot t mod m of the rings belongs to step t."""

    level: np.ndarray
    trend: np.ndarray
    season: np.ndarray  # m x R
    alpha: np.ndarray
    beta: np.ndarray
    gamma: np.ndarray


class Scales:
    """Squared error scales of coordinates; one that was never observed has the start value.

    An array over the slice while that is small, else a dictionary of the coordinates touched.
    """

    LIMIT = 4_000_000

    def __init__(self, sizes, known=()):
        self.sizes = tuple(int(s) for s in sizes)
        size = int(np.prod([float(s) for s in self.sizes]))
        self.dense = np.full(size, np.nan) if size <= self.LIMIT else None
        self.sparse: dict[tuple, float] = {}
        for k, v in known:
            self.put(np.array([k], np.int64), np.array([v]))

    def _flat(self, idx):
        return np.ravel_multi_index(idx.T, self.sizes)

    def get(self, idx: np.ndarray, start: float) -> np.ndarray:
        if self.dense is None:
            return np.array([self.sparse.get(k, start) for k in map(tuple, idx.tolist())], float)
        v = self.dense[self._flat(idx)] if len(idx) else np.empty(0)
        return np.where(np.isnan(v), start, v)

    def put(self, idx: np.ndarray, values: np.ndarray) -> None:
        if self.dense is None:
            self.sparse.update(zip(map(tuple, idx.tolist()), values.tolist()))
        elif len(idx):
            self.dense[self._flat(idx)] = values

    def items(self):
        if self.dense is None:
            return list(self.sparse.items())
        on = np.flatnonzero(~np.isnan(self.dense))
        return list(zip(map(tuple, np.stack(np.unravel_index(on, self.sizes), 1).tolist()), self.dense[on].tolist()))

    def copy(self) -> Scales:
        out = Scales.__new__(Scales)
        out.sizes, out.dense, out.sparse = self.sizes, None if self.dense is None else self.dense.copy(), dict(self.sparse)
        return out

    def __len__(self) -> int:
        return len(self.sparse) if self.dense is None else int((~np.isnan(self.dense)).sum())

    def __eq__(self, other) -> bool:
        return isinstance(other, Scales) and dict(self.items()) == dict(other.items())


@dataclass
class Snapshot:
    """Everything that the next step needs; independent of how many steps have passed."""

    factors: list[np.ndarray]
    season: SeasonState
    ring: np.ndarray  # m x R, time vectors of the last m steps
    t: int  # last step that was processed
    scales: Scales | None = None

    def __post_init__(self):
        if self.scales is None:
            self.scales = Scales([len(u) for u in self.factors])

    def copy(self) -> Snapshot:
        s = self.season
        return Snapshot([u.copy() for u in self.factors], SeasonState(s.level.copy(), s.trend.copy(), s.season.copy(), s.alpha, s.beta, s.gamma), self.ring.copy(), self.t, self.scales.copy())
