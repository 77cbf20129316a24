"""Points inside strata: the mean of b uniforms per axis, or the centre."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import rng


def mean_uniform(seed: int, tag: str, b: int, *keys: Column) -> Column:
    """Mean of ``b`` keyed uniforms; its spread falls with b."""
    if b < 1:
        raise ValueError("b must be positive")
    if b == 1:
        return rng.uniform(seed, tag, *keys, 1)
    each = [rng.uniform(seed, tag, *keys, k) for k in range(1, b + 1)]
    return sum(each[1:], each[0]) / F.lit(float(b))


def draw(strata: DataFrame, b: int | None = 1, seed: int = 0, copies: int = 1, first_copy: int = 0) -> DataFrame:
    """``strata`` with point_id, copy and x: one point per stratum and copy.

    ``b`` None gives the centre. Each number depends on seed, stratum, copy and
    axis alone, so tasks may be repeated or dealt anew.
    """
    out = strata.withColumn("copy", F.explode(F.sequence(F.lit(first_copy), F.lit(first_copy + copies - 1)))) if copies != 1 or first_copy else strata.withColumn("copy", F.lit(0))
    if b is None:
        x = F.zip_with("lo", "hi", lambda low, h: (low + h) / 2)
    else:
        index = F.sequence(F.lit(0), F.size("lo") - 1)
        x = F.transform(index, lambda d: _inside(F.element_at("lo", d + 1), F.element_at("hi", d + 1), mean_uniform(seed, "draw", b, F.col("stratum_id"), F.col("copy"), d)))
    return out.select(F.col("stratum_id").alias("point_id"), *strata.columns, "copy", x.alias("x"))


def _inside(lo: Column, hi: Column, u: Column) -> Column:
    return lo + (hi - lo) * u


def augment(strata: DataFrame, k: int, b: int | None = 1, seed: int = 0) -> DataFrame:
    """k further points in every kept stratum; the first draw was copy 0."""
    return draw(strata, b, seed, copies=k, first_copy=1)


def draw_np(lo: np.ndarray, hi: np.ndarray, b: int | None, *keys: int) -> np.ndarray:
    if b is None:
        return (lo + hi) / 2
    row, dim = np.arange(len(lo))[:, None], np.arange(lo.shape[1])[None, :]
    u = sum(rng.fast_uniform(*keys, 3, k, row, dim) for k in range(b)) / b
    return lo + (hi - lo) * u
