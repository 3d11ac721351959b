"""One online step over a slice that is too large for a task.

Cells of the slice meet their error scales (a sparse table of touched coordinates, the start value elsewhere),
and one pass in the tasks gives residuals, new scales and the gradient sums of all modes and of the time
vector together. The exchange carries at most (touched rows) x (R + 1) numbers a task.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HyperParams, Snapshot, TensorSpec
from ..plans import startup
from ..sources.tables import staged
from . import kernel


def advance(state: Snapshot, cells: DataFrame, scales: DataFrame | None, spec: TensorSpec, hp: HyperParams) -> tuple[Snapshot, DataFrame]:
    """(new state, judged cells with y_hat, outlier and sigma2) of one slice (modes.., y).

    scales: (modes.., sigma2) of earlier steps or None. The judged cells are persisted; their sigma2 is the
    delta that `overlay` writes over the scales.
    """
    modes, rank = spec.modes, spec.rank
    start = (hp.lambda3 * hp.floor) ** 2
    w_hat = kernel.predict_time(state)
    rows = cells.select(*modes, "y")
    rows = rows.withColumn("sigma2", F.lit(start)) if scales is None else rows.join(scales.select(*modes, "sigma2"), modes, "left").withColumn("sigma2", F.coalesce("sigma2", F.lit(start)))
    shared = cells.sparkSession.sparkContext.broadcast((state.factors, w_hat))

    def judge(batches):
        import pyarrow as pa

        factors, w = shared.value
        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in modes], 1).astype(np.int64)
            y, s2 = (batch.column(k).to_numpy(zero_copy_only=False) for k in ("y", "sigma2"))
            y_hat = kernel.rows(factors, idx) @ w
            s = np.sqrt(s2)
            z = (y - y_hat) / s
            r = kernel.psi(z, hp.k) * s
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in modes), pa.array(y), pa.array(y_hat), pa.array(y - y_hat - r), pa.array(s2 * (1 - hp.phi + hp.phi * kernel.rho(z, hp.k, hp.c_k))), pa.array(r)], [*modes, "y", "y_hat", "outlier", "sigma2", "r"])

    schema = ", ".join(f"{m} int" for m in modes) + ", y double, y_hat double, outlier double, sigma2 double, r double"
    judged = rows.select(*[F.col(m).cast("int").alias(m) for m in modes], "y", "sigma2").mapInArrow(judge, schema).persist()
    names = [f"g{a}" for a in range(rank)] + ["size"]

    def gradients(batches):
        import pyarrow as pa

        factors, w = shared.value
        sums = [np.zeros((len(u), rank + 1)) for u in factors] + [np.zeros((1, rank + 1))]
        seen = False
        for batch in batches:
            seen = seen or batch.num_rows > 0
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in modes], 1).astype(np.int64)
            r = batch.column("r").to_numpy(zero_copy_only=False)
            for n in range(len(factors) + 1):
                h = kernel.rows(factors, idx, n) * w if n < len(factors) else kernel.rows(factors, idx)
                np.add.at(sums[n], idx[:, n] if n < len(factors) else np.zeros(len(r), np.int64), np.c_[r[:, None] * h, (h * h).sum(1)])
        if seen:
            for n, s in enumerate(sums):
                on = np.flatnonzero(np.abs(s).sum(1))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(on), n, np.int32)), pa.array(on, pa.int64()), *(pa.array(s[on, j]) for j in range(rank + 1))], ["mode", "row", *names])

    part = judged.select(*modes, "r").mapInArrow(gradients, "mode int, row long, " + ", ".join(f"{c} double" for c in names))
    got = part.groupBy("mode", "row").agg(*[F.sum(c).alias(c) for c in names]).toPandas()  # touched rows of the modes
    return apply(state, w_hat, got, rank, hp), judged


def apply(state: Snapshot, w_hat: np.ndarray, sums, rank: int, hp: HyperParams) -> Snapshot:
    """The new state from the summed gradients (mode, row, g.., size)."""
    m, t = len(state.ring), state.t + 1
    slot, scaled = t % m, hp.step_rule == "row_scaled"
    new = []
    for n, u in enumerate(state.factors):
        own = sums[sums["mode"] == n]
        g = own[[f"g{a}" for a in range(rank)]].to_numpy()
        if scaled:
            size = own["size"].to_numpy()
            g = g / np.where(size > 0, size, 1.0)[:, None]
        u = u.copy()
        u[own["row"].to_numpy(dtype=np.int64)] += 2 * hp.mu * g
        new.append(u)
    own = sums[sums["mode"] == len(state.factors)]
    total = own[[f"g{a}" for a in range(rank)]].to_numpy().sum(0) if len(own) else np.zeros(rank)
    size = float(own["size"].sum()) if len(own) else 0.0
    pull = total + hp.lambda1 * (state.ring[state.t % m] - w_hat) + hp.lambda2 * (state.ring[slot] - w_hat)
    if scaled:
        pull = pull / max(size + hp.lambda1 + hp.lambda2, 1e-300)
    w = w_hat + 2 * hp.mu * pull
    new, w = kernel.finished(new, w, t, hp)
    ring = state.ring.copy()
    ring[slot] = w
    return Snapshot(new, kernel.update_season(state.season, w, slot), ring, t, state.scales)


def overlay(scales: DataFrame | None, judged: DataFrame, spec: TensorSpec) -> DataFrame:
    """The scales with the touched coordinates' new values over them."""
    delta = judged.select(*spec.modes, F.col("sigma2").alias("new"))
    if scales is None:
        return delta.withColumnRenamed("new", "sigma2")
    return scales.join(delta, spec.modes, "full_outer").select(*spec.modes, F.coalesce("new", "sigma2").alias("sigma2"))


def run(cells: DataFrame, spec: TensorSpec, hp: HyperParams, starts: int = 1) -> DataFrame:
    """(modes.., t, y_hat, x_hat, outlier) of every step after the start-up, to the stream's end, one step over the cluster
    at a time. Of `starts` random start-ups the one with the least absolute residual is kept. Judged slices and the sparse
    scales are staged after each step, so no plan grows with the stream."""
    cells = staged(cells.select(*spec.modes, "t", "y"), "cells")
    state = startup.snapshot(startup.best(cells, spec, hp, starts), spec)
    scales = out = None
    last = cells.agg(F.max("t")).first()[0]
    shown = lambda state: cells.sparkSession.sparkContext.broadcast((state.factors, state.ring[state.t % len(state.ring)]))
    for t in range(spec.startup, (-1 if last is None else last) + 1):
        state, judged = advance(state, cells.where(F.col("t") == t), scales, spec, hp)
        scales = staged(overlay(scales, judged, spec), "scales")
        part = staged(imputed(judged, shown(state), spec).select(*spec.modes, F.lit(t).alias("t"), "y_hat", "x_hat", "outlier"), "judged")
        judged.unpersist()
        out = part if out is None else out.unionByName(part)
    schema = ", ".join(f"{m} int" for m in spec.modes) + ", t int, y_hat double, x_hat double, outlier double"
    return out if out is not None else cells.sparkSession.createDataFrame([], schema)


def imputed(judged: DataFrame, shared, spec: TensorSpec) -> DataFrame:
    """judged with x_hat, the cell's value after the step."""
    from pyspark.sql.types import DoubleType, StructType

    def run(batches):
        import pyarrow as pa

        factors, w = shared.value
        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in spec.modes], 1).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(kernel.rows(factors, idx) @ w)], [*batch.schema.names, "x_hat"])

    return judged.mapInArrow(run, StructType([*judged.schema.fields]).add("x_hat", DoubleType()))
