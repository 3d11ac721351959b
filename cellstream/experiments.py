"""The experiments: start-up accuracy, imputation, speed, forecasting, scalability and the choice of rank.

Streams are planted on the coordinates of the given tables' cubes: a closed low-rank seasonal value at every coordinate,
observed where the cube has a cell and a hash draw does not drop it, so that the tables' real gaps count. A group of runs
is one (workload, corruption, seed), dealt to the tasks as rows; in it every method sees the same cells. Rivals' settings
are chosen by a grid for each workload, on a seed and corruption of its own. Results are rows, one a step, method and run.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines.registry import MAKERS
from .model import HyperParams, TensorSpec
from .operators import corrupt, metrics
from .operators.corrupt import apply_dense
from .plans import startup
from .sources import cubes, planted
from .sources.tables import load, staged
from .streaming import kernel
from .streaming.fold import Stream

#: Mildest and harshest as published, the two between are ours.
LEVELS = [(20, 10, 2), (30, 15, 3), (50, 20, 4), (70, 20, 5)]
SEEDS = (1, 2, 3, 4, 5)
#: The cubes that stand for the four published streams.
WORKLOADS = ["sensor_hour", "flow_month", "transition_hour", "orders_day"]
SHAPES = {w: (cubes.CUBES[w].sizes, cubes.CUBES[w].steps, cubes.CUBES[w].period) for w in WORKLOADS}
OWN = "robust_seasonal"
IMPUTERS = [OWN, "sgd_stream_cp", "rls_stream_cp", "multi_aspect_stream", "slab_robust_stream"]
FORECASTERS = [OWN, "seasonal_stream_mf", "static_cp_forecast"]
#: Missing percent at which the proposed method forecasts; rivals see every cell.
MISSING = (0, 30, 70)
HORIZON, RANK, TUNING_SEED, TUNING_LEVEL = 24, 3, 0, (30, 15, 3)
#: Tasks that groups of runs are dealt to; a number of its own, so that they are not put together for being small.
TASKS = 160
#: Settings that a rival's grid search tries.
GRIDS = {
    "sgd_stream_cp": [{"step": a, "ridge": b} for a in (0.03, 0.1, 0.3) for b in (1e-3, 1e-1)],
    "rls_stream_cp": [{"forget": a} for a in (0.9, 0.98, 0.999)],
    "multi_aspect_stream": [{"forget": a} for a in (0.5, 0.9, 0.98)],
    "slab_robust_stream": [{"forget": a, "slab": b} for a in (0.9, 0.98) for b in (1.0, 5.0)],
    "seasonal_stream_mf": [{"step": a} for a in (0.03, 0.1, 0.3)],
    "static_cp_forecast": [{"sweeps": a} for a in (30, 60)],
}
STEP_SCHEMA = "workload string, missing int, outliers int, times int, seed int, method string, settings string, t int, nre double, seconds double"


def hyper(y: np.ndarray) -> HyperParams:
    """Step and smoothness settings of all experiments, one for every workload; the first threshold follows the data's scale."""
    return HyperParams(lambda1=0.01, lambda2=0.01, lambda3=float(max(1.0, 10 * np.median(np.abs(y)))), max_iter=100)


class Robust:
    def __init__(self, spec: TensorSpec, hp: HyperParams, seed: int = 0):
        self.stream = Stream(spec, hp.with_(seed=seed), 3)
        self.spec, self.t = spec, -1

    def start(self):
        """Runs the start-up, if it is not done yet; its time does not count as a step's."""
        if self.stream.state is None:
            self.stream.begin()

    def feed(self, idx, y):
        self.t += 1
        self.stream.feed(self.t, idx, y)

    def impute(self, idx):
        return kernel.impute(self.stream.state, idx)

    def forecast(self, idx, h):
        return kernel.forecast(self.stream.state, idx, h)


def make(method: str, spec: TensorSpec, hp: HyperParams, seed: int, settings: dict | None = None):
    return Robust(spec, hp, seed) if method == OWN else MAKERS[method](spec, seed=seed, **(settings or {}))


def coordinates(spec_sizes) -> np.ndarray:
    return np.stack(np.unravel_index(np.arange(int(np.prod(spec_sizes))), spec_sizes), 1)


def imputed(method: str, spec: TensorSpec, x: np.ndarray, slices: list, hp: HyperParams, seed: int, settings: dict | None = None) -> list[tuple[int, float, float]]:
    """(t, relative error, seconds) of every step after the start-up. x: truth, modes by time; slices: (idx, y) of each step."""
    model, out = make(method, spec, hp, seed, settings), []
    full = coordinates(spec.sizes)
    for t, (idx, y) in enumerate(slices):
        if t == spec.startup and method == OWN:
            model.start()
        began = time.perf_counter()
        model.feed(idx, y)
        took = time.perf_counter() - began
        if t >= spec.startup:
            truth = x[..., t].ravel()
            with np.errstate(all="ignore"):
                out.append((t, float(np.linalg.norm(model.impute(full) - truth) / np.linalg.norm(truth)), took))
    return out


def forecast(method: str, spec: TensorSpec, x: np.ndarray, slices: list, hp: HyperParams, seed: int, settings: dict | None = None) -> list[tuple[int, float, float]]:
    """(t, relative error, seconds a step) of the last HORIZON steps, forecast from the end of the others.

    A method that is rerun from scratch at each step costs a whole rerun; one is timed, over the full history.
    """
    model, took, steps = make(method, spec, hp, seed, settings), [], x.shape[-1]
    full = coordinates(spec.sizes)
    for t in range(steps - HORIZON):
        if t == spec.startup and method == OWN:
            model.start()
        began = time.perf_counter()
        model.feed(*slices[t])
        if t >= spec.startup:
            took.append(time.perf_counter() - began)
    if not getattr(model, "online", True):
        began = time.perf_counter()
        model.refit()
        took = [time.perf_counter() - began] * 2
    seconds, out = metrics.art(took), []
    for h in range(1, HORIZON + 1):
        t = steps - HORIZON - 1 + h
        truth = x[..., t].ravel()
        out.append((t, float(np.linalg.norm(model.forecast(full, h) - truth) / np.linalg.norm(truth)), seconds))
    return out


def sliced(pdf, steps: int, modes: list[str]) -> list:
    """(idx, y) of every step, from a group's cells."""
    pdf = pdf.sort_values(["t", *modes])
    t, idx, y = pdf["t"].to_numpy(), pdf[modes].to_numpy(np.int64), pdf["y"].to_numpy(float)
    edge = np.searchsorted(t, np.arange(steps + 1))
    return [(idx[a:b], y[a:b]) for a, b in zip(edge, edge[1:])]


def observed(spark: SparkSession, d: str, workload: str, levels, seeds, whole: bool = False) -> DataFrame:
    """(workload, missing, outliers, times, seed, i1, i2, t, y) of the runs' cells: planted values at the cube's
    coordinates (whole: at all), with hash-drawn gaps and outliers."""
    sizes, steps, m = SHAPES[workload]
    if whole:
        at = spark.range(int(np.prod(sizes)) * steps).select((F.col("id") % sizes[0]).cast("int").alias("i1"), (F.floor(F.col("id") / sizes[0]) % sizes[1]).cast("int").alias("i2"), F.floor(F.col("id") / int(np.prod(sizes))).cast("int").alias("t"))
    else:
        at = cubes.cells(spark, d, workload).where((F.col("t") >= 0) & (F.col("t") < steps)).select("i1", "i2", "t")
    out = None
    for seed in seeds:
        truth = planted.truth(at, ["i1", "i2"], RANK, m, seed)
        largest = float(planted.values(sizes, steps, RANK, m, seed).max())
        for level in levels:
            rows = corrupt.apply(truth, ["i1", "i2", "t"], *level, seed=1000 + seed, largest=largest)
            rows = rows.select(F.lit(workload).alias("workload"), *[F.lit(int(v)).alias(c) for v, c in zip(level, ("missing", "outliers", "times"))], F.lit(int(seed)).alias("seed"), "i1", "i2", "t", "y")
            out = rows if out is None else out.unionByName(rows)
    return out


def runs(cells: DataFrame, methods: dict[str, list[dict]] | list[str], measure, chosen: dict | None = None) -> DataFrame:
    """Rows of STEP_SCHEMA: every method on every group of cells, a group a task.

    methods: names with the settings to try; chosen: settings by (workload, method) instead.
    """
    import json

    def go(key, pdf):
        import pandas as pd

        workload, *level, seed = key[0], *map(int, key[1:])
        sizes, steps, m = SHAPES[workload]
        spec, x = TensorSpec(sizes, m, RANK), planted.values(sizes, steps, RANK, m, seed)
        slices = sliced(pdf, steps, ["i1", "i2"])
        hp = hyper(pdf["y"].to_numpy())
        rows = []
        for name in methods:
            for settings in [json.loads(chosen.get((workload, name), "{}"))] if chosen is not None else methods[name]:
                try:
                    got = measure(name, spec, x, slices, hp, seed, settings)
                except (kernel.Diverged, np.linalg.LinAlgError, ValueError):
                    got = [(-1, float("inf"), float("nan"))]  # the run broke off; it counts as no result
                rows += [(workload, *level, seed, name, json.dumps(settings, sort_keys=True), *g) for g in got]
        return pd.DataFrame(rows, columns=[c.split()[0] for c in STEP_SCHEMA.split(", ")])

    by = ["workload", "missing", "outliers", "times", "seed"]
    return cells.repartition(TASKS, *by).groupBy(*by).applyInPandas(go, STEP_SCHEMA)


def mean_error(rows: DataFrame, *more: str) -> DataFrame:
    """The running average error and time of every run: mean over its steps (a broken run's is infinite)."""
    by = ["workload", "missing", "outliers", "times", "method", *more]
    return rows.groupBy(*by).agg(F.avg("nre").alias("rae"), (F.sum("seconds") / F.greatest(F.count(F.lit(1)) - 1, F.lit(1))).alias("art"))


def tuned(rows: DataFrame) -> dict:
    """The settings with the least error by workload and method."""
    best = mean_error(rows, "settings").groupBy("workload", "method").agg(F.min_by("settings", F.struct("rae", "settings")).alias("settings"))
    return {(r["workload"], r["method"]): r["settings"] for r in best.collect()}  # a row a workload and method


_kept: dict[tuple, DataFrame] = {}


def kept(name: str, spark: SparkSession, d: str, build) -> DataFrame:
    """The table of a grid of runs, made once a session and table folder: several measures are read off one grid."""
    key = (name, spark.sparkContext.applicationId, d)
    if key not in _kept:
        _kept[key] = staged(build(), name)
    return _kept[key]


def union(parts) -> DataFrame:
    out = None
    for p in parts:
        out = p if out is None else out.unionByName(p)
    return out


def imputation_runs(spark: SparkSession, d: str) -> DataFrame:
    """Every imputer on four streams, four corruptions and five seeds; rivals tuned."""
    def build():
        rivals = {m: GRIDS[m] for m in IMPUTERS if m != OWN}
        trial = union(observed(spark, d, w, [TUNING_LEVEL], [TUNING_SEED]) for w in WORKLOADS)
        chosen = tuned(runs(trial, rivals, imputed))
        cells = union(observed(spark, d, w, LEVELS, SEEDS) for w in WORKLOADS)
        return runs(cells, IMPUTERS, imputed, chosen)

    return kept("imputation", spark, d, build)


def forecasting_runs(spark: SparkSession, d: str) -> DataFrame:
    """The proposed method at three rates of missing cells on the cubes' coordinates, rivals on complete streams;
    20 % outliers of five times the maximum for all."""
    def build():
        rivals = {m: GRIDS[m] for m in FORECASTERS if m != OWN}
        trial = union(observed(spark, d, w, [(0, 20, 5)], [TUNING_SEED], True) for w in WORKLOADS)
        chosen = tuned(runs(trial, rivals, forecast))
        own = union(observed(spark, d, w, [(x, 20, 5) for x in MISSING], SEEDS, True) for w in WORKLOADS)
        rest = union(observed(spark, d, w, [(0, 20, 5)], SEEDS, True) for w in WORKLOADS)
        return runs(own, [OWN], forecast, {}).unionByName(runs(rest, list(rivals), forecast, chosen))

    return kept("forecasting", spark, d, build)


def compared(rows: DataFrame, by: list[str]) -> DataFrame:
    """For each workload (and what else is in `by`): the proposed method's error and time, means over the seeds, and the
    most accurate other's; how many percent less the error is, and how many times faster."""
    mean = rows.groupBy(*by, "method", "seed").agg(F.avg("nre").alias("error"), (F.sum("seconds") / F.greatest(F.count(F.lit(1)) - 1, F.lit(1))).alias("art")).groupBy(*by, "method").agg(F.avg("error").alias("error"), F.avg("art").alias("art"))
    own = mean.where(F.col("method") == OWN).select(*by, F.col("error").alias("own_error"), F.col("art").alias("own_art"))
    second = mean.where(F.col("method") != OWN).groupBy(*by).agg(F.min_by(F.struct("method", "error", "art"), F.struct("error", "method")).alias("s"))
    out = own.join(second, by)
    return out.select(*by, "own_error", "own_art", F.col("s.method").alias("second"), F.col("s.error").alias("second_error"), F.col("s.art").alias("second_art"), (100 * (1 - F.col("own_error") / F.col("s.error"))).alias("percent_less_error"), (F.col("s.art") / F.col("own_art")).alias("times_faster"))


# ---- runs on whole planted tensors


#: Ten ranks between 4 and 20.
RANKS = (4, 5, 6, 8, 10, 12, 14, 16, 18, 20)


def planted_run(method: str, workload: str, level, seed: int, steps: int | None = None, rank: int = RANK, planted_rank: int = RANK, hp_change: dict | None = None) -> dict[str, float]:
    """Running average error and mean seconds a step, on a full grid with dense corruption."""
    sizes, all_steps, m = SHAPES[workload]
    x, _ = planted.dense(sizes, steps or all_steps, planted_rank, m, seed)
    y, mask = apply_dense(x, *level, seed=seed + 1000)
    slices = [(np.argwhere(mask[..., t]), y[..., t][mask[..., t]]) for t in range(x.shape[-1])]
    got = imputed(method, TensorSpec(sizes, m, rank), x, slices, hyper(y[mask]).with_(**(hp_change or {})), seed)
    return {"rae": float(np.mean([g[1] for g in got])), "art": metrics.art([g[2] for g in got])}


def planted_forecast(method: str, workload: str, missing: int, seed: int) -> dict[str, float]:
    """Average forecasting error on a full grid with 20 % outliers of 5 times the maximum; rivals see every cell."""
    sizes, steps, m = SHAPES[workload]
    x, _ = planted.dense(sizes, steps, RANK, m, seed)
    y, mask = apply_dense(x, missing if method == OWN else 0, 20, 5, seed=seed + 1000)
    slices = [(np.argwhere(mask[..., t]), y[..., t][mask[..., t]]) for t in range(steps)]
    got = forecast(method, TensorSpec(sizes, m, RANK), x, slices, hyper(y[mask]), seed)
    return {"afe": float(np.mean([g[1] for g in got])), "art": got[0][2]}


def rank_choice(workload: str, seed: int, ranks=RANKS, level=(20, 10, 2)) -> dict[int, float]:
    """Running average error by rank of the model, on a planted stream of rank 4."""
    return {r: planted_run(OWN, workload, level, seed, None, r, 4, {"max_iter": 40})["rae"] for r in ranks}


def start_up(solver: str, level, seed: int, shape=((30, 30), 90, 30), rank: int = 3) -> list[tuple[int, float, float]]:
    """(outer iteration, error of the time factor, error of the tensor) over a start-up."""
    sizes, steps, m = shape
    x, truth = planted.dense(sizes, steps, rank, m, seed)
    y, mask = apply_dense(x, *level, seed=seed + 1000)
    return start_up_errors(solver, seed, np.argwhere(mask), y[mask], TensorSpec(sizes, m, rank), x, truth)


def start_up_errors(solver: str, seed: int, idx, y, spec: TensorSpec, x, truth) -> list[tuple[int, float, float]]:
    """The same, on observed cells idx, y of the tensor x with the factors truth."""
    trace = []
    startup.run_local(idx, y, spec, HyperParams(lambda1=0.01, lambda2=0.01, max_iter=150), x.shape[-1], solver, trace, seed)
    scaled = truth[-1] * np.prod([np.linalg.norm(u, axis=0) for u in truth[:-1]], 0)
    size = np.linalg.norm(x)
    return [(k + 1, metrics.factor_nre(f[-1], scaled), float(np.linalg.norm(np.einsum("ir,jr,tr->ijt", *f) - x) / size)) for k, f in enumerate(trace)]


def scalability(sizes: tuple[int, int], steps: int, m: int = 10, rank: int = 3, seed: int = 0) -> list[float]:
    """Seconds of every step after the start-up, on complete clean slices that are made one at a time."""
    rng = np.random.default_rng(seed)
    factors = [rng.random((s, rank)) for s in sizes]
    a, b, c = rng.uniform(-2, 2, rank), rng.uniform(0, 2 * np.pi, rank), rng.uniform(-2, 2, rank)
    w = a * np.sin(2 * np.pi * np.arange(steps)[:, None] / m + b) + c
    spec = TensorSpec(sizes, m, rank)
    state = startup.snapshot([*[u.copy() for u in factors], w[: spec.startup].copy()], spec)
    idx = coordinates(sizes)
    took = []
    for t in range(spec.startup, steps):
        y = kernel.rows(factors, idx) @ w[t]
        began = time.perf_counter()
        state, _ = kernel.advance(state, idx, y, HyperParams(), True)
        took.append(time.perf_counter() - began)
    return took


def start_up_runs(spark: SparkSession, d: str, level=(90, 20, 7), workload: str = "flow_month") -> DataFrame:
    """solver, seed, iteration, factor_nre, nre: both solvers, five seeds, every outer iteration, on the cells that the cube has."""
    def go(pdf):
        import pandas as pd

        solver, seed = pdf["solver"].iloc[0], int(pdf["seed"].iloc[0])
        sizes, steps, m = SHAPES[workload]
        pdf = pdf.sort_values(["t", "i1", "i2"])
        x, truth = planted.values(sizes, steps, RANK, m, seed), planted.factors(sizes, steps, RANK, m, seed)
        got = start_up_errors(solver, seed, pdf[["i1", "i2", "t"]].to_numpy(np.int64), pdf["y"].to_numpy(float), TensorSpec(sizes, m, RANK), x, truth)
        return pd.DataFrame([(solver, seed, *g) for g in got], columns=["solver", "seed", "iteration", "factor_nre", "nre"])

    cells = staged(observed(spark, d, workload, [level], SEEDS).select("seed", "i1", "i2", "t", "y"), "start_up")
    cells = cells.withColumn("solver", F.explode(F.array(F.lit("smooth"), F.lit("plain"))))
    return cells.repartition(TASKS, "solver", "seed").groupBy("solver", "seed").applyInPandas(go, "solver string, seed int, iteration int, factor_nre double, nre double")


def scalability_runs(spark: SparkSession, d: str, side: int = 500, firsts=tuple(range(50, 501, 50)), m: int = 10) -> DataFrame:
    """axis, rows, cells, steps, seconds: a step's median time by the first mode's size, and the total time by the number of
    steps on the smallest slices. Slices are of line items: orders by parts, each dealt to `side` indices, by month, and
    by day for the steps; y is of their quantity. A slice's cells are its given ones. One task, so that runs do not slow
    each other; it holds one slice at a time."""
    item = load(spark, d, "lineitem").where("l_shipdate is not null").select(F.pmod("l_orderkey", F.lit(side)).cast("int").alias("i1"), F.pmod("l_partkey", F.lit(side)).cast("int").alias("i2"), "l_shipdate", "l_quantity")
    month = (F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1
    parts = {"cells": (item, month), "steps": (item.where(F.col("i1") < firsts[0]), cubes.day("l_shipdate", "1995-01-01"))}
    cells = None
    for axis, (rows, t) in parts.items():
        c = rows.groupBy(F.lit(axis).alias("axis"), t.cast("int").alias("t"), "i1", "i2").agg(F.log2(1 + F.sum("l_quantity")).alias("y"))
        cells = c if cells is None else cells.unionByName(c)

    def go(batches):
        import pandas as pd

        rng = np.random.default_rng(0)
        states, took, seen = {}, {}, {}

        def begin(first, y):
            u = [rng.uniform(0.5, 1, (n, RANK)) for n in (first, side)]
            w = np.full((3 * m, RANK), float(np.mean(y)) / RANK / 0.5625)
            return startup.snapshot([*u, w], TensorSpec((first, side), m, RANK))

        def step(axis, pdf):
            pdf = pdf.sort_values(["i1", "i2"])
            idx, y = pdf[["i1", "i2"]].to_numpy(np.int64), pdf["y"].to_numpy(float)
            for first in firsts if axis == "cells" else firsts[:1]:
                n, key = int(np.searchsorted(idx[:, 0], first)), (axis, first)
                if key not in states:
                    if not n:
                        continue
                    states[key], took[key], seen[key] = begin(first, y[:n]), [], []
                began = time.perf_counter()
                states[key], _ = kernel.advance(states[key], idx[:n], y[:n], HyperParams(), True)
                took[key].append(time.perf_counter() - began)
                seen[key].append(n)

        held = None
        for pdf in batches:
            held = pdf if held is None else pd.concat([held, pdf])
            *whole, last = [g for _, g in held.groupby(["axis", "t"], sort=True)] or [held]
            for g in whole:
                step(g["axis"].iloc[0], g)
            held = last
        if held is not None and len(held):
            step(held["axis"].iloc[0], held)
        out = [("cells", f, int(np.mean(seen[a, f])), len(took[a, f]), float(np.median(took[a, f]))) for a, f in took if a == "cells"]
        for a, f in took:
            if a == "steps":
                total = np.cumsum(took[a, f])
                marks = np.unique(np.linspace(len(total) // 10, len(total) - 1, 10).astype(int))
                out += [("steps", f, int(np.mean(seen[a, f])), int(k) + 1, float(total[k])) for k in marks]
        yield pd.DataFrame(out, columns=["axis", "rows", "cells", "steps", "seconds"])

    return cells.repartition(1).sortWithinPartitions("axis", "t").mapInPandas(go, "axis string, rows int, cells int, steps int, seconds double")


def linear(rows: DataFrame) -> DataFrame:
    """axis, slope, r2 of the straight line through seconds against cells or steps."""
    n = F.when(F.col("axis") == "cells", F.col("cells")).otherwise(F.col("steps")).cast("double")
    return rows.groupBy("axis").agg(F.regr_slope("seconds", n).alias("slope"), F.regr_r2("seconds", n).alias("r2"))


def running(rows: DataFrame) -> DataFrame:
    """rows with the mean error up to each step."""
    by = Window.partitionBy("workload", "missing", "outliers", "times", "seed", "method").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("rae", F.avg("nre").over(by))
