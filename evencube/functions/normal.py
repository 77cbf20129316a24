"""Inverse normal and log-normal distribution functions as Columns and NumPy."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# A published rational approximation of the inverse normal (relative error below 1.2e-9).
A = (-3.969683028665376e01, 2.209460984245205e02, -2.759285104469687e02, 1.383577518672690e02, -3.066479806614716e01, 2.506628277459239e00)
B = (-5.447609879822406e01, 1.615858368580409e02, -1.556989798598866e02, 6.680131188771972e01, -1.328068155288572e01)
C = (-7.784894002430293e-03, -3.223964580411365e-01, -2.400758277161838e00, -2.549732539343734e00, 4.374664141464968e00, 2.938163982698783e00)
D = (7.784695709041462e-03, 3.224671290700398e-01, 2.445134137142996e00, 3.754408661907416e00)
LOW = 0.02425
#: Nearest to 0 and 1 that a probability is taken.
TINY = 1e-15


def _poly(coefficients: Sequence[float], v):
    out = coefficients[0]
    for c in coefficients[1:]:
        out = out * v + c
    return out


def norm_ppf(p: Column) -> Column:
    p = F.least(F.greatest(p, F.lit(TINY)), F.lit(1 - TINY))
    q, r = p - 0.5, (p - 0.5) * (p - 0.5)
    middle = q * _poly(A, r) / (_poly(B, r) * r + 1)
    tail = F.sqrt(-2 * F.log(F.least(p, 1 - p)))
    outer = _poly(C, tail) / (_poly(D, tail) * tail + 1)
    return F.when(p < LOW, outer).when(p > 1 - LOW, -outer).otherwise(middle)


def norm_ppf_np(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, TINY, 1 - TINY)
    q = p - 0.5
    r = q * q
    middle = q * _poly(A, r) / (_poly(B, r) * r + 1)
    tail = np.sqrt(-2 * np.log(np.minimum(p, 1 - p)))
    outer = _poly(C, tail) / (_poly(D, tail) * tail + 1)
    return np.where(p < LOW, outer, np.where(p > 1 - LOW, -outer, middle))


def lognormal_shape(mean: float, cv: float) -> tuple[float, float]:
    """(mu, sigma) of the logarithm from mean and coefficient of variation."""
    s2 = math.log(1 + cv * cv)
    return math.log(mean) - s2 / 2, math.sqrt(s2)


def normal(p: Column, mean: float, cv: float) -> Column:
    return F.lit(mean) + F.lit(mean * cv) * norm_ppf(p)


def lognormal(p: Column, mean: float, cv: float) -> Column:
    mu, sigma = lognormal_shape(mean, cv)
    return F.exp(F.lit(mu) + F.lit(sigma) * norm_ppf(p))
