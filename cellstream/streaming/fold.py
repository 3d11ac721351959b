"""The online method over many tensors at once: a task folds over a tensor's slices in order of t.

One exchange by tensor_id, a sort that spills, then one pass: only one slice and the state are held. A tensor
whose slices are themselves huge goes through streaming.step instead (plans.planner chooses).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HyperParams, Snapshot, TensorSpec
from ..plans import startup
from . import kernel

OUTPUT = "tensor_id string, {modes}, t int, kind string, x_hat double, outlier double"


def slices(batches, modes: list[str]):
    """(tensor_id, t, idx, y) of each slice, from record batches sorted by tensor_id and t."""
    held, key = [], None

    def out():
        idx = np.concatenate([a for a, _ in held])
        return key[0], key[1], idx, np.concatenate([b for _, b in held])

    for batch in batches:
        if not batch.num_rows:
            continue
        ids, t = batch.column("tensor_id").to_pylist(), batch.column("t").to_numpy(zero_copy_only=False)
        idx = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in modes], 1).astype(np.int64)
        y = batch.column("y").to_numpy(zero_copy_only=False).astype(float)
        new = [0, *(k for k in range(1, len(t)) if t[k] != t[k - 1] or ids[k] != ids[k - 1]), len(t)]
        for a, b in zip(new, new[1:]):
            at = (ids[a], int(t[a]))
            if key is not None and at != key:
                if at[0] == key[0] and at[1] < key[1]:
                    raise ValueError(f"slices out of order: {at} after {key}")
                yield out()
                held = []
            key = at
            held.append((idx[a:b], y[a:b]))
    if held:
        yield out()


class Stream:
    """Buffers the start-up slices of one tensor, then takes slices one by one, empty ones in between included."""

    def __init__(self, spec: TensorSpec, hp: HyperParams, starts: int = 3, state: Snapshot | None = None):
        self.spec, self.hp, self.starts, self.state, self.buffer, self.found = spec, hp, starts, state, [], []

    def feed(self, t: int, idx: np.ndarray, y: np.ndarray):
        """[(kind, t, idx, x_hat, outlier)] of the steps that this slice completes."""
        out = []
        if self.state is None:
            if t < self.spec.startup:
                self.buffer.append((t, idx, y))
                return out
            out += self.begin()
        while self.state.t + 1 < t:
            self.state, _ = kernel.advance(self.state, np.empty((0, len(self.spec.sizes)), np.int64), np.empty(0), self.hp, True)
        if t <= self.state.t:
            return out  # a slice that was processed already, as after a replay
        self.state, got = kernel.advance(self.state, idx, y, self.hp, True)
        out.append(("update", t, idx, kernel.impute(self.state, idx), got["outlier"]))
        return out

    def begin(self):
        if not self.buffer:
            raise ValueError(f"no cell in the start-up of {self.spec.startup} steps")
        idx = np.concatenate([np.c_[i, np.full(len(i), t)] for t, i, _ in self.buffer])
        y = np.concatenate([v for _, _, v in self.buffer])
        factors, o = startup.best_local(idx, y, self.spec, self.hp, self.spec.startup, self.starts)
        self.state = startup.snapshot(factors, self.spec)
        self.buffer = []
        x = startup.smooth_als.products(factors, idx).sum(1)
        return [("startup", int(t), idx[on][:, :-1], x[on], o[on]) for t in np.unique(idx[:, -1]) for on in [idx[:, -1] == t]]


def run(cells: DataFrame, spec: TensorSpec, hp: HyperParams, horizon: int = 0, impute: bool = True, starts: int = 3, limit: int = 2_000_000, short: str = "raise") -> DataFrame:
    """(tensor_id, modes.., t, kind, x_hat, outlier) for cells (tensor_id, modes.., t, y).

    kind: startup and update for observed cells, imputed for the others of an updated slice, forecast for
    `horizon` steps past each tensor's end. A full slice has prod(sizes) cells; where that is over `limit`, ask
    for single coordinates by plans.planner.impute_at instead. A tensor shorter than the start-up is an error, or with
    short="mark" gives its cells as kind too_short, without values, and leaves the other tensors alone.
    """
    modes = spec.modes
    if (impute or horizon) and int(np.prod(spec.sizes)) > limit:
        raise ValueError("full slices of this size are not made in a task")
    grid = np.stack(np.unravel_index(np.arange(int(np.prod(spec.sizes))), spec.sizes), 1) if impute or horizon else None

    def batch(tensor, parts):
        import pyarrow as pa

        idx = np.concatenate([p[2] for p in parts])
        n = [len(p[2]) for p in parts]
        return pa.RecordBatch.from_arrays(
            [pa.array([tensor] * len(idx), pa.string()), *(pa.array(idx[:, k].astype(np.int32)) for k in range(len(modes))), pa.array(np.repeat([p[1] for p in parts], n).astype(np.int32)), pa.array([p[0] for p in parts for _ in range(len(p[2]))], pa.string()), pa.array(np.concatenate([p[3] for p in parts])), pa.array(np.concatenate([p[4] for p in parts]))],
            ["tensor_id", *modes, "t", "kind", "x_hat", "outlier"],
        )

    def missing(stream, idx):
        on = np.ones(len(grid), bool)
        on[np.ravel_multi_index(idx.T, spec.sizes)] = False
        return ("imputed", stream.state.t, grid[on], kernel.impute(stream.state, grid[on]), np.zeros(int(on.sum())))

    def finish(tensor, stream):
        out = []
        if stream.state is None and stream.buffer:
            if max(t for t, _, _ in stream.buffer) + 1 < spec.startup:
                if short == "mark":
                    return [("too_short", t, idx, np.full(len(idx), np.nan), np.zeros(len(idx))) for t, idx, _ in stream.buffer]
                raise ValueError(f"tensor {tensor} ends before its start-up of {spec.startup} steps")
            out += stream.begin()
        for h in range(1, horizon + 1):
            out.append(("forecast", stream.state.t + h, grid, kernel.forecast(stream.state, grid, h), np.zeros(len(grid))))
        return [o for o in out if len(o[2])]

    def go(batches):
        stream, current = None, None
        for tensor, t, idx, y in slices(batches, modes):
            if tensor != current:
                if stream is not None and (rest := finish(current, stream)):
                    yield batch(current, rest)
                stream, current = Stream(spec, hp, starts), tensor
            got = stream.feed(t, idx, y)
            if impute and got and got[-1][0] == "update":
                got.append(missing(stream, idx))
            if got := [g for g in got if len(g[2])]:
                yield batch(tensor, got)
        if stream is not None and (rest := finish(current, stream)):
            yield batch(current, rest)

    columns = ["tensor_id", *modes, "t", "y"]
    dealt = cells.select(*columns).repartition("tensor_id").sortWithinPartitions("tensor_id", "t", *modes)
    return dealt.mapInArrow(go, OUTPUT.format(modes=", ".join(f"{m} int" for m in modes)))
