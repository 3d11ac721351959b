"""Bounded-influence functions as native columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

K, C_K = 2.0, 2.52


def huber_psi(x: Column, k: float = K) -> Column:
    return F.greatest(F.least(x, F.lit(k)), F.lit(-k))


def biweight_rho(x: Column, k: float = K, c: float = C_K) -> Column:
    inner = 1 - (x / k) * (x / k)
    return F.when(F.abs(x) <= k, c * (1 - inner * inner * inner)).otherwise(F.lit(c))


def soft_threshold(x: Column, threshold: float | Column) -> Column:
    return F.signum(x) * F.greatest(F.abs(x) - threshold, F.lit(0.0))


def clean(y: Column, forecast: Column, sigma: Column, k: float = K) -> Column:
    """The observation with what lies beyond k error scales cut off."""
    return forecast + huber_psi((y - forecast) / sigma, k) * sigma


def outlier(y: Column, forecast: Column, sigma: Column, k: float = K) -> Column:
    return y - clean(y, forecast, sigma, k)


def scale_update(sigma2: Column, error: Column, phi: float, k: float = K, c: float = C_K) -> Column:
    """Squared error scale after one error."""
    return sigma2 * (1 - phi + phi * biweight_rho(error / F.sqrt(sigma2), k, c))
