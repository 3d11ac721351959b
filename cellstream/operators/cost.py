"""The objectives, term by term."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def masked_loss(cells: DataFrame) -> DataFrame:
    """Half the squared residual over observed cells (y, x_hat)."""
    r = F.col("y") - F.col("x_hat")
    return cells.agg((0.5 * F.sum(r * r)).alias("loss"))


def smoothness(time_factor: DataFrame, lag: int) -> DataFrame:
    """(t, d2): squared distance of each time row (t, vec) to the one `lag` before; 0 where there is none.

    The time factor has one row a step; its window is the one place where all steps meet in order.
    """
    before = F.lag("vec", lag).over(Window.orderBy("t"))
    d2 = F.aggregate(F.zip_with("vec", before, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    return time_factor.select("t", F.coalesce(d2, F.lit(0.0)).alias("d2"))


def step_terms(cells: DataFrame, time_factor: DataFrame, m: int, l1: float, l2: float, l3: float) -> DataFrame:
    """(t, fit, smooth, seasonal, sparse): the weighted terms of each step; cells have y, x_hat, o."""
    r = F.col("y") - F.col("o") - F.col("x_hat")
    fit = cells.groupBy("t").agg(F.sum(r * r).alias("fit"), (l3 * F.sum(F.abs("o"))).alias("sparse"))
    one = smoothness(time_factor, 1).select("t", (l1 * F.col("d2")).alias("smooth"))
    two = smoothness(time_factor, m).select("t", (l2 * F.col("d2")).alias("seasonal"))
    return one.join(two, "t").join(fit, "t", "left").select("t", F.coalesce("fit", F.lit(0.0)).alias("fit"), "smooth", "seasonal", F.coalesce("sparse", F.lit(0.0)).alias("sparse"))


def batch(terms: DataFrame) -> DataFrame:
    sums = [F.sum(c).alias(c) for c in ("fit", "smooth", "seasonal", "sparse")]
    return terms.agg(*sums).withColumn("total", F.col("fit") + F.col("smooth") + F.col("seasonal") + F.col("sparse"))


def stream(terms: DataFrame) -> DataFrame:
    """The streaming objective up to each step; its last value is the batch objective."""
    total = F.col("fit") + F.col("smooth") + F.col("seasonal") + F.col("sparse")
    running = F.sum(total).over(Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0))
    return terms.select("t", total.alias("step"), running.alias("running"))
