"""Losses as column expressions and as numpy functions."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def mse(y: Column, forecast: Column) -> Column:
    return (forecast - y) * (forecast - y)


def gaussian_nll(y: Column, loc: Column, scale: Column) -> Column:
    z = (y - loc) / scale
    return F.lit(0.5 * math.log(2 * math.pi)) + F.log(scale) + F.lit(0.5) * z * z


def student_nll(y: Column, loc: Column, scale: Column, df: float) -> Column:
    const = math.lgamma(df / 2) - math.lgamma((df + 1) / 2) + 0.5 * math.log(df * math.pi)
    z = (y - loc) / scale
    return F.lit(const) + F.log(scale) + F.lit((df + 1) / 2) * F.log1p(z * z / df)


def mape(y: Column, forecast: Column, zero: str = "skip", eps: float = 1e-8) -> Column:
    """Null at a zero target (an average skips it), or divided by at least eps."""
    if zero == "skip":
        return F.abs(forecast - y) / F.nullif(F.abs(y), F.lit(0.0))
    return F.abs(forecast - y) / F.greatest(F.abs(y), F.lit(eps))


def pinball(y: Column, forecast: Column, q: float) -> Column:
    e = y - forecast
    return F.greatest(F.lit(q) * e, F.lit(q - 1) * e)


def kl_gaussian(loc: Column, scale: Column, loc0: Column, scale0: Column) -> Column:
    """Divergence of N(loc, scale) from N(loc0, scale0)."""
    d = loc - loc0
    return F.log(scale0 / scale) + (scale * scale + d * d) / (F.lit(2.0) * scale0 * scale0) - F.lit(0.5)


def kl_discrete(p: Column, q: Column) -> Column:
    """Divergence of two arrays of probabilities; a zero in p adds nothing."""
    return F.aggregate(F.zip_with(p, q, lambda a, b: F.when(a > 0, a * F.log(a / b)).otherwise(F.lit(0.0))), F.lit(0.0), lambda s, x: s + x)


def np_mse(y: np.ndarray, forecast: np.ndarray) -> float:
    return float(np.mean((forecast - y) ** 2))


def np_gaussian_nll(y: np.ndarray, loc: np.ndarray, scale: np.ndarray) -> float:
    return float(np.mean(0.5 * math.log(2 * math.pi) + np.log(scale) + 0.5 * ((y - loc) / scale) ** 2))


def np_student_nll(y: np.ndarray, loc: np.ndarray, scale: np.ndarray, df: float) -> float:
    const = math.lgamma(df / 2) - math.lgamma((df + 1) / 2) + 0.5 * math.log(df * math.pi)
    return float(np.mean(const + np.log(scale) + (df + 1) / 2 * np.log1p(((y - loc) / scale) ** 2 / df)))


def np_mape(y: np.ndarray, forecast: np.ndarray) -> float:
    keep = y != 0
    return float(np.mean(np.abs(forecast - y)[keep] / np.abs(y)[keep])) if keep.any() else float("nan")


def np_pinball(y: np.ndarray, forecast: np.ndarray, q: float) -> float:
    e = y - forecast
    return float(np.mean(np.maximum(q * e, (q - 1) * e)))
