"""Missing entries and outliers, drawn by a hash of the coordinates: the same cells however data are dealt."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def draw(on: list[str], seed: int, salt: int) -> Column:
    """A number in [0, 1) for each coordinate."""
    h = F.xxhash64(F.lit(seed), F.lit(salt), *on)
    return F.pmod(h, F.lit(1 << 52)) / float(1 << 52)


def apply(truth: DataFrame, on: list[str], missing: float, outliers: float, times: float, seed: int = 0, how: str = "add", largest: float | None = None) -> DataFrame:
    """(on.., y, o) of the observed cells of truth (on.., x): `missing` and `outliers` in percent, drawn
    independently; an outlier is +-times the largest value, added to the value or in its place."""
    if largest is None:
        largest = truth.agg(F.max("x")).first()[0] or 0.0
    sign = F.when(draw(on, seed, 3) < 0.5, -1.0).otherwise(1.0)
    o = F.when(draw(on, seed, 2) < outliers / 100, sign * times * largest).otherwise(0.0)
    y = F.col("x") + o if how == "add" else F.when(o != 0, o).otherwise(F.col("x"))
    return truth.where(draw(on, seed, 1) >= missing / 100).select(*on, y.alias("y"), (y - F.col("x")).alias("o"))


def apply_dense(truth, missing: float, outliers: float, times: float, seed: int):
    """The same model on a numpy tensor: (y, mask)."""
    import numpy as np

    rng = np.random.default_rng(seed)
    mask = rng.random(truth.shape) >= missing / 100
    hit = rng.random(truth.shape) < outliers / 100
    sign = np.where(rng.random(truth.shape) < 0.5, -1.0, 1.0)
    return truth + hit * sign * times * truth.max(), mask
