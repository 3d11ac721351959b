"""Level-trend-season smoothing of many series: a fold over each series' ordered values, inside the JVM.

State: level, trend, season (array of the last m), and what a caller wants out of each step. Series are keyed;
one series is one array, so its length is bounded by what a task holds; longer streams go through
streaming.fold, which keeps the state only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .robust import biweight_rho, huber_psi


def ordered(series: DataFrame, key: str = "key") -> DataFrame:
    """(key, ys): the values of each series by t."""
    return series.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "y"))), lambda p: p["y"]).alias("ys"))


def initial(ys: Column, m: int) -> tuple[Column, Column, Column]:
    """Level, trend and seasons from the first two seasons: mean, mean change a step, and differences to the mean."""
    mean = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x) / m
    one, two = mean(F.slice(ys, 1, m)), mean(F.slice(ys, m + 1, m))
    return one, (two - one) / m, F.transform(F.slice(ys, 1, m), lambda x: x - one)


def _rotate(season: Column, new: Column) -> Column:
    return F.concat(F.slice(season, F.lit(2), F.size(season) - 1), F.array(new))


def fold(ys: Column, level: Column, trend: Column, season: Column, alpha, beta, gamma, kind: str = "additive", robust: str = "", phi: float = 0.1, sigma2: Column | None = None, k: float = 2.0) -> Column:
    """The struct (level, trend, season, sigma2, sse, path) after all of ys; path: (level, trend, season, yhat, clean) of each step.

    robust: '' none; 'scale_first' updates the error scale and cleans with it; 'reject_first' cleans with the
    scale before, then updates.
    """
    a, b, g = (x if isinstance(x, Column) else F.lit(float(x)) for x in (alpha, beta, gamma))
    path_type = "array<struct<level:double,trend:double,season:double,yhat:double,clean:double>>"
    start = F.struct(
        level.cast("double").alias("level"),
        trend.cast("double").alias("trend"),
        season.cast("array<double>").alias("season"),
        (F.lit(1.0) if sigma2 is None else sigma2).cast("double").alias("sigma2"),
        F.lit(0.0).alias("sse"),
        F.array().cast(path_type).alias("path"),
    )

    def step(s: Column, y: Column) -> Column:
        old = s["season"][0]
        yhat = s["level"] + s["trend"] + old if kind == "additive" else (s["level"] + s["trend"]) * old
        e = y - yhat
        moved = s["sigma2"] * (1 - phi + phi * biweight_rho(e / F.sqrt(s["sigma2"]), k))
        if robust == "scale_first":
            used = F.sqrt(moved)
        else:
            used = F.sqrt(s["sigma2"])
        v = huber_psi(e / used, k) * used + yhat if robust else y
        base = s["level"] + s["trend"]
        if kind == "additive":
            new_level = a * (v - old) + (1 - a) * base
            new_season = g * (v - base) + (1 - g) * old
        else:
            new_level = a * (v / old) + (1 - a) * base
            new_season = g * (v / base) + (1 - g) * old
        new_trend = b * (new_level - s["level"]) + (1 - b) * s["trend"]
        return F.struct(
            new_level.alias("level"),
            new_trend.alias("trend"),
            _rotate(s["season"], new_season).alias("season"),
            (moved if robust else s["sigma2"]).alias("sigma2"),
            (s["sse"] + e * e).alias("sse"),
            F.concat(s["path"], F.array(F.struct(new_level.alias("level"), new_trend.alias("trend"), new_season.alias("season"), yhat.alias("yhat"), v.alias("clean")))).alias("path"),
        )

    return F.aggregate(ys, start, step)


def forecast(state: Column, h: Column, m: int, kind: str = "additive") -> Column:
    """h steps past the end; the season index stays in the last known season."""
    base = state["level"] + h * state["trend"]
    season = F.element_at(state["season"], (F.pmod(h - 1, F.lit(m)) + 1).cast("int"))
    return base + season if kind == "additive" else base * season
