"""Planted streams: low rank, seasonal, with a closed formula, on a full grid or a table cube's coordinates."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def factor_value(mode: int, idx: Column, r: int, seed: int = 0) -> Column:
    """Entry of a non-temporal factor: a formula of mode, index and component; seeds shift its phase."""
    return 0.6 + 0.4 * F.cos((idx + 1) * (1.7 * mode + 0.9 * r + 1.1) + 1.3 * seed * (r + 1))


def time_value(t: Column, r: int, m: int, seed: int = 0) -> Column:
    return (r + 1) * F.sin(2 * math.pi * t / m + 0.8 * r + 0.7 * seed * (r + 1)) + 1.5 - 0.4 * r + 0.002 * (r + 1) * t


def truth(coords: DataFrame, modes: list[str], rank: int, m: int, seed: int = 0) -> DataFrame:
    """coords with x, the planted value."""
    x = F.lit(0.0)
    for r in range(rank):
        term = time_value(F.col("t"), r, m, seed)
        for n, mode in enumerate(modes):
            term = term * factor_value(n, F.col(mode), r, seed)
        x = x + term
    return coords.withColumn("x", x)


def values(sizes: tuple[int, ...], steps: int, rank: int, m: int, seed: int = 0) -> np.ndarray:
    """The same formula as an array of all coordinates, time last."""
    t, out = np.arange(steps), 0.0
    for r in range(rank):
        term = (r + 1) * np.sin(2 * math.pi * t / m + 0.8 * r + 0.7 * seed * (r + 1)) + 1.5 - 0.4 * r + 0.002 * (r + 1) * t
        for n in reversed(range(len(sizes))):
            u = 0.6 + 0.4 * np.cos((np.arange(sizes[n]) + 1) * (1.7 * n + 0.9 * r + 1.1) + 1.3 * seed * (r + 1))
            term = np.multiply.outer(u, term)
        out = out + term
    return out


def factors(sizes: tuple[int, ...], steps: int, rank: int, m: int, seed: int = 0) -> list[np.ndarray]:
    """The factors of the same formula, time last."""
    r, t = np.arange(rank), np.arange(steps)[:, None]
    out = [0.6 + 0.4 * np.cos((np.arange(n)[:, None] + 1) * (1.7 * k + 0.9 * r + 1.1) + 1.3 * seed * (r + 1)) for k, n in enumerate(sizes)]
    return [*out, (r + 1) * np.sin(2 * math.pi * t / m + 0.8 * r + 0.7 * seed * (r + 1)) + 1.5 - 0.4 * r + 0.002 * (r + 1) * t]


def dense(sizes: tuple[int, ...], steps: int, rank: int, m: int, seed: int = 0, dist: str = "uniform") -> tuple[np.ndarray, list[np.ndarray]]:
    """(tensor, factors) with sinusoidal time columns a * sin(2 pi i / m + b) + c, a and c in [-2, 2], b in [0, 2 pi]."""
    rng = np.random.default_rng(seed)
    factors = [rng.random((s, rank)) if dist == "uniform" else rng.standard_normal((s, rank)) for s in sizes]
    a, b, c = rng.uniform(-2, 2, rank), rng.uniform(0, 2 * np.pi, rank), rng.uniform(-2, 2, rank)
    i = np.arange(steps)[:, None]
    factors.append(a * np.sin(2 * np.pi * i / m + b) + c)
    letters = "abcdefgh"[: len(factors)]
    return np.einsum(",".join(f"{x}r" for x in letters) + "->" + letters, *factors), factors
