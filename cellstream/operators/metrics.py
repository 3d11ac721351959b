"""Accuracy and cost measures."""

from __future__ import annotations

from itertools import permutations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def nre(cells: DataFrame) -> DataFrame:
    """(t, nre) from cells with x (truth) and x_hat, over all coordinates given."""
    d = F.col("x_hat") - F.col("x")
    return cells.groupBy("t").agg((F.sqrt(F.sum(d * d)) / F.sqrt(F.sum(F.col("x") * F.col("x")))).alias("nre"))


def rae(per_step: DataFrame) -> DataFrame:
    return per_step.agg(F.avg("nre").alias("rae"))


def afe(cells: DataFrame) -> DataFrame:
    """Mean over the forecast horizon of each slice's relative error."""
    return nre(cells).agg(F.avg("nre").alias("afe"))


def art(times: list[float], divisor: str = "paper") -> float:
    """Mean time of the steps after the start-up; the published divisor is one less than their number."""
    return sum(times) / max(1, len(times) - (divisor == "paper"))


def art_rows(times: DataFrame, by: str, column: str) -> DataFrame:
    """(by, paper, mean) of the times of each run with two steps at least: both divisors."""
    n = F.count(F.lit(1))
    return times.groupBy(by).agg(F.round(F.sum(column) / (n - 1), 6).alias("paper"), F.round(F.avg(column), 6).alias("mean"), n.alias("n")).where("n > 1").drop("n")


def relative_change(cells: DataFrame) -> DataFrame:
    """Frobenius norm of new - old over that of old."""
    d = F.col("x_new") - F.col("x_old")
    return cells.agg((F.sqrt(F.sum(d * d)) / F.sqrt(F.sum(F.col("x_old") * F.col("x_old")))).alias("change"))


def outlier_pr(flagged: DataFrame, injected: DataFrame, on: list[str]) -> DataFrame:
    """Precision and recall of flagged cells."""
    f, i = flagged.select(*on).distinct(), injected.select(*on).distinct()
    hit = f.join(i, on, "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    sizes = f.agg(F.count(F.lit(1)).alias("flagged")).crossJoin(i.agg(F.count(F.lit(1)).alias("injected")))
    return hit.crossJoin(sizes).select("hits", "flagged", "injected", (F.col("hits") / F.greatest("flagged", F.lit(1))).alias("precision"), (F.col("hits") / F.greatest("injected", F.lit(1))).alias("recall"))


def factor_nre(found: np.ndarray, planted: np.ndarray) -> float:
    """Relative error of a factor after the best matching of components, each freely scaled and signed."""
    rank = planted.shape[1]

    def scaled(u, v):
        d = u @ u
        return u * ((u @ v) / d) if d > 0 else u

    cost = np.array([[((scaled(found[:, a], planted[:, b]) - planted[:, b]) ** 2).sum() for b in range(rank)] for a in range(found.shape[1])])
    if rank <= 7:
        best = min(sum(cost[a, b] for b, a in enumerate(p)) for p in permutations(range(found.shape[1]), rank))
    else:
        best, left = 0.0, set(range(found.shape[1]))
        for b in np.argsort(cost.min(0)):
            a = min(left, key=lambda a: cost[a, b])
            left.discard(a)
            best += cost[a, b]
    return float(np.sqrt(best) / np.linalg.norm(planted))


def slope(x: list[float], y: list[float]) -> tuple[float, float, float]:
    """Least-squares line: slope, intercept, R squared."""
    x, y = np.array(x, float), np.array(y, float)
    b, a = np.polyfit(x, y, 1)
    ss = ((y - y.mean()) ** 2).sum()
    return float(b), float(a), float(1 - ((y - a - b * x) ** 2).sum() / ss) if ss else 1.0
