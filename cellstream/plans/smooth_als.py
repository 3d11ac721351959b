"""Alternating least squares on observed cells, with a temporally and seasonally smooth time factor.

Two drivers share the solvers: `fit_local` on numpy arrays, for a start-up window that one task holds (many
tensors run side by side), and `fit` on a DataFrame, where each mode's normal equations are partial sums in the
tasks, then one exchange of at most (rows of the mode) x R (R + 3) / 2 numbers a task. Only row systems reach
the driver; cells stay where they are.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HyperParams, TensorSpec

#: Numbers of one mode's rows that may come to the driver, and of its row systems that a task sums before it sends them.
MOST_NUMBERS, TASK_NUMBERS = 50_000_000, 20_000_000


def drawn(mode: int, rows: np.ndarray, rank: int, seed: int, salt: int = 0) -> np.ndarray:
    """Numbers in (0, 1) for (row, component) of a mode, from a hash of them: the same wherever they are made."""
    x = np.asarray(rows, np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(rank, dtype=np.uint64) * np.uint64(0xBF58476D1CE4E5B9)
    x = x + np.uint64((seed * 0x94D049BB133111EB + mode * 0xD6E8FEB86659FD93 + salt * 0xA0761D6478BD642F + 1) % 2**64)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    x = x ^ (x >> np.uint64(31))
    return ((x >> np.uint64(11)).astype(float) + 0.5) / 2**53


def initial_factors(sizes: tuple[int, ...], rank: int, seed: int, dist: str = "uniform") -> list[np.ndarray]:
    """Random factors; dist: uniform in (0, 1), or normal."""
    out = []
    for n, s in enumerate(sizes):
        u = drawn(n, np.arange(s), rank, seed)
        out.append(u if dist == "uniform" else np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * drawn(n, np.arange(s), rank, seed, 1)))
    return out


def products(factors: list[np.ndarray], idx: np.ndarray, skip: int | None = None) -> np.ndarray:
    """Element-wise product of each cell's factor rows, but for the skipped mode's."""
    h = np.ones((len(idx), factors[0].shape[1]))
    for n, u in enumerate(factors):
        if n != skip:
            h = h * u[idx[:, n]]
    return h


def systems(h: np.ndarray, y: np.ndarray, rows: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Gram matrices and right sides of every row of a mode."""
    rank = h.shape[1]
    gram, right = np.empty((size, rank, rank)), np.empty((size, rank))
    for a in range(rank):
        right[:, a] = np.bincount(rows, y * h[:, a], minlength=size)
        for b in range(a, rank):
            gram[:, a, b] = gram[:, b, a] = np.bincount(rows, h[:, a] * h[:, b], minlength=size)
    return gram, right


def solve_rows(gram: np.ndarray, right: np.ndarray, old: np.ndarray) -> np.ndarray:
    """Rows of a non-temporal factor; a row without cells keeps its old value, a singular one takes the pseudo-inverse."""
    out = old.copy()
    on = np.flatnonzero(np.trace(gram, axis1=1, axis2=2) > 0)
    if len(on):
        try:
            x = np.linalg.solve(gram[on], right[on][..., None])[..., 0]
            bad = ~np.isfinite(x).all(1) | (np.linalg.cond(gram[on]) > 1e12)
        except np.linalg.LinAlgError:
            x, bad = np.zeros((len(on), right.shape[1])), np.ones(len(on), bool)
        for i in np.flatnonzero(bad):
            x[i] = np.linalg.pinv(gram[on[i]]) @ right[on[i]]
        out[on] = x
    return out


def time_rows(gram: np.ndarray, right: np.ndarray, w: np.ndarray, m: int, l1: float, l2: float, order: str = "gauss_seidel") -> np.ndarray:
    """Time rows with pulls to the neighbours that exist at distance 1 and m.

    gauss_seidel: in place, ascending; jacobi: all from the old rows; joint: one solve for all rows.
    """
    steps, rank = w.shape
    near = [[(s, l) for s, l in ((t - 1, l1), (t + 1, l1), (t - m, l2), (t + m, l2)) if 0 <= s < steps] for t in range(steps)]
    eye = np.eye(rank)
    if order == "joint":
        big = np.zeros((steps * rank, steps * rank))
        for t in range(steps):
            at = slice(t * rank, (t + 1) * rank)
            big[at, at] = gram[t] + sum(l for _, l in near[t]) * eye
            for s, l in near[t]:
                big[at, s * rank : (s + 1) * rank] -= l * eye
        return np.linalg.lstsq(big, right.ravel(), rcond=None)[0].reshape(steps, rank)
    out = w.copy()
    source = out if order == "gauss_seidel" else w
    for t in range(steps):
        weight = sum(l for _, l in near[t])
        b = gram[t] + weight * eye
        c = right[t] + sum((l * source[s] for s, l in near[t]), np.zeros(rank))
        if not b.any():
            continue
        try:
            out[t] = np.linalg.solve(b, c)
        except np.linalg.LinAlgError:
            out[t] = np.linalg.pinv(b) @ c
    return out


def normalize(factors: list[np.ndarray], n: int) -> None:
    """Columns of mode n to norm 1, their norms to the time factor; a zero column stays."""
    norms = np.linalg.norm(factors[n], axis=0)
    norms = np.where(norms > 0, norms, 1.0)
    factors[n] /= norms
    factors[-1] *= norms


def fitness(y: np.ndarray, x: np.ndarray) -> float:
    total = np.linalg.norm(y)
    return 1 - np.linalg.norm(y - x) / total if total > 0 else 1.0


def sweep(factors: list[np.ndarray], idx: np.ndarray, y: np.ndarray, m: int, hp: HyperParams) -> None:
    """One pass over all modes, in place."""
    last = len(factors) - 1
    for n in range(last):
        gram, right = systems(products(factors, idx, n), y, idx[:, n], len(factors[n]))
        factors[n] = solve_rows(gram, right, factors[n])
        normalize(factors, n)
    gram, right = systems(products(factors, idx, last), y, idx[:, last], len(factors[last]))
    factors[last] = time_rows(gram, right, factors[last], m, hp.lambda1, hp.lambda2, hp.time_order)


def fit_local(factors: list[np.ndarray], idx: np.ndarray, y: np.ndarray, m: int, hp: HyperParams) -> float:
    """Sweeps until the fitness settles or inner_max_iter; returns the fitness."""
    before = -np.inf
    for _ in range(hp.inner_max_iter):
        sweep(factors, idx, y, m, hp)
        now = fitness(y, products(factors, idx).sum(1))
        if abs(now - before) < hp.tol:
            break
        before = now
    return now


def cleaned(fs, frozen, threshold: float, idx: np.ndarray, y: np.ndarray) -> np.ndarray:
    """y without the outliers that the frozen factors see: residuals are cut at the threshold."""
    if frozen is None:
        return y
    r = y - products(frozen, idx).sum(1)
    return y - np.sign(r) * np.maximum(np.abs(r) - threshold, 0)


def row_sums(cells: DataFrame, factors: list[np.ndarray], names: list[str], n: int, outliers: tuple | None = None) -> tuple[DataFrame, list[str], list[str], object]:
    """(row, g.., c..): upper Gram entries and right sides of mode n summed over cells (names.., y) without moving them.

    outliers: (frozen factors, threshold) whose outliers are taken off y in the same pass.
    """
    rank, size = factors[0].shape[1], len(factors[n])
    pairs = [(a, b) for a in range(rank) for b in range(a, rank)]
    frozen, threshold = outliers or (None, 0.0)
    shared = cells.sparkSession.sparkContext.broadcast((factors, frozen))  # rows of all modes, of checked size
    grams, rights = [f"g{i}" for i in range(len(pairs))], [f"c{a}" for a in range(rank)]
    whole = size * rank * rank <= TASK_NUMBERS

    def run(batches):
        import numpy as np
        import pyarrow as pa

        fs, before = shared.value

        def rows_of(on, part):
            return pa.RecordBatch.from_arrays([pa.array(on, pa.int64()), *(pa.array(part[:, j]) for j in range(part.shape[1]))], ["row", *grams, *rights])

        total = None
        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in names], 1).astype(np.int64)
            y = cleaned(fs, before, threshold, idx, batch.column("y").to_numpy(zero_copy_only=False))
            on, at = (None, idx[:, n]) if whole else np.unique(idx[:, n], return_inverse=True)
            gram, right = systems(products(fs, idx, n), y, at, size if whole else len(on))
            part = np.concatenate([np.stack([gram[:, a, b] for a, b in pairs], 1), right], 1)
            if whole:
                total = part if total is None else total + part
            elif len(on):  # a long mode: a batch's touched rows leave at once
                yield rows_of(on, part)
        if total is not None:
            on = np.flatnonzero(np.abs(total).sum(1))
            yield rows_of(on, total[on])

    schema = "row long, " + ", ".join(f"{c} double" for c in [*grams, *rights])
    out = cells.select(*names, "y").mapInArrow(run, schema).groupBy("row").agg(*[F.sum(c).alias(c) for c in [*grams, *rights]])
    return out, grams, rights, shared


def unpacked(got, rank: int, grams: list[str], rights: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Gram matrices and right sides from columns of sums."""
    gram, k = np.zeros((len(got), rank, rank)), 0
    for a in range(rank):
        for b in range(a, rank):
            gram[:, a, b] = gram[:, b, a] = got[grams[k]].to_numpy()
            k += 1
    return gram, np.stack([got[c].to_numpy() for c in rights], 1) if len(got) else np.zeros((0, rank))


def row_systems(cells: DataFrame, factors: list[np.ndarray], names: list[str], n: int, outliers: tuple | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Gram matrices and right sides of every row of mode n, on the driver: for the time mode, whose rows hang together."""
    rank, size = factors[0].shape[1], len(factors[n])
    if size * rank * rank > MOST_NUMBERS:
        raise ValueError(f"mode {names[n]}: row systems of {size} x {rank} x {rank} numbers are over {MOST_NUMBERS}")
    sums, grams, rights, shared = row_sums(cells, factors, names, n, outliers)
    got = sums.toPandas()  # of checked size
    shared.unpersist()
    gram, right = np.zeros((size, rank, rank)), np.zeros((size, rank))
    at = got["row"].to_numpy(dtype=np.int64)
    gram[at], right[at] = unpacked(got, rank, grams, rights)
    return gram, right


def solved_rows(cells: DataFrame, factors: list[np.ndarray], names: list[str], n: int, outliers: tuple | None = None) -> np.ndarray:
    """The new rows of a non-temporal mode, solved in the tasks that hold their sums; R numbers a row come back."""
    rank, size = factors[0].shape[1], len(factors[n])
    if size * rank > MOST_NUMBERS:
        raise ValueError(f"mode {names[n]}: {size} x {rank} numbers are over {MOST_NUMBERS}; its factor is not held on the driver")
    sums, grams, rights, shared = row_sums(cells, factors, names, n, outliers)
    columns = [f"u{a}" for a in range(rank)]

    def solve(batches):
        import pyarrow as pa

        for batch in batches:
            got = batch.to_pandas()
            gram, right = unpacked(got, rank, grams, rights)
            at = got["row"].to_numpy(dtype="int64")
            u = solve_rows(gram, right, shared.value[0][n][at])
            yield pa.RecordBatch.from_arrays([pa.array(at), *(pa.array(u[:, a]) for a in range(rank))], ["row", *columns])

    got = sums.mapInArrow(solve, "row long, " + ", ".join(f"{c} double" for c in columns)).toPandas()  # of checked size
    shared.unpersist()
    out = factors[n].copy()
    out[got["row"].to_numpy(dtype=np.int64)] = got[columns].to_numpy()
    return out


def residuals(cells: DataFrame, factors: list[np.ndarray], names: list[str]) -> DataFrame:
    """cells with x_hat."""
    shared = cells.sparkSession.sparkContext.broadcast(factors)

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in names], 1).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(products(shared.value, idx).sum(1))], [*batch.schema.names, "x_hat"])

    from pyspark.sql.types import DoubleType, StructType

    return cells.mapInArrow(run, StructType([*cells.schema.fields]).add("x_hat", DoubleType()))


def sweep_distributed(cells: DataFrame, factors: list[np.ndarray], spec: TensorSpec, hp: HyperParams, outliers: tuple | None = None) -> None:
    """As sweep, over a DataFrame of cells (modes.., t, y)."""
    names, last = [*spec.modes, "t"], len(factors) - 1
    for n in range(last):
        factors[n] = solved_rows(cells, factors, names, n, outliers)
        normalize(factors, n)
    factors[last] = time_rows(*row_systems(cells, factors, names, last, outliers), factors[last], spec.period, hp.lambda1, hp.lambda2, hp.time_order)


def fitness_distributed(cells: DataFrame, factors: list[np.ndarray], names: list[str], outliers: tuple | None = None) -> float:
    """The fitness over a DataFrame of cells: two sums a task."""
    frozen, threshold = outliers or (None, 0.0)
    shared = cells.sparkSession.sparkContext.broadcast((factors, frozen))

    def run(batches):
        import pyarrow as pa

        fs, before = shared.value
        error = size = 0.0
        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in names], 1).astype(np.int64)
            y = cleaned(fs, before, threshold, idx, batch.column("y").to_numpy(zero_copy_only=False))
            error, size = error + float(((y - products(fs, idx).sum(1)) ** 2).sum()), size + float((y**2).sum())
        yield pa.RecordBatch.from_arrays([pa.array([error]), pa.array([size])], ["error", "size"])

    error, size = cells.select(*names, "y").mapInArrow(run, "error double, size double").agg(F.sum("error"), F.sum("size")).first()
    shared.unpersist()
    return 1 - np.sqrt(error) / np.sqrt(size) if size else 1.0


def fit_distributed(cells: DataFrame, factors: list[np.ndarray], spec: TensorSpec, hp: HyperParams, outliers: tuple | None = None, trace: list | None = None) -> None:
    """As fit_local, over a DataFrame: sweeps until the fitness settles, or inner_max_iter; one sweep asks for no fitness."""
    before = -np.inf
    for _ in range(hp.inner_max_iter):
        sweep_distributed(cells, factors, spec, hp, outliers)
        if hp.inner_max_iter > 1 or trace is not None:
            now = fitness_distributed(cells, factors, [*spec.modes, "t"], outliers)
            if trace is not None:
                trace.append(now)
            if abs(now - before) < hp.tol:
                break
            before = now


def kruskal_inner(f: list[np.ndarray], g: list[np.ndarray]) -> float:
    """Inner product of two low-rank tensors from R x R matrices alone."""
    out = 1.0
    for u, v in zip(f, g):
        out = out * (u.T @ v)
    return float(np.sum(out))


def relative_change(new: list[np.ndarray], old: list[np.ndarray]) -> float:
    before = kruskal_inner(old, old)
    change = kruskal_inner(new, new) - 2 * kruskal_inner(new, old) + before
    return float(np.sqrt(max(change, 0.0) / before)) if before > 0 else np.inf
