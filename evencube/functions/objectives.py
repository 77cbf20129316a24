"""Integrands and objectives, as Column expressions over an array and as NumPy functions over rows."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .. import rng
from .normal import lognormal, lognormal_shape, normal, norm_ppf_np

# Mean and coefficient of variation of the plate's inputs, in order.
PLATE = (
    ("width", "normal", 0.992 * 36, 0.028),
    ("thickness", "lognormal", 1.05 * 0.75, 0.044),
    ("yield", "lognormal", 1.3 * 34, 0.1235),
    ("modulus", "normal", 0.987 * 29000, 0.076),
    ("deflection", "normal", 0.35, 0.05),
    ("residual", "normal", 5.25, 0.07),
)


def sphere(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda acc, v: acc + v * v)


def rosenbrock(x: Column) -> Column:
    pairs = F.zip_with(F.slice(x, 1, F.size(x) - 1), F.slice(x, 2, F.size(x) - 1), lambda a, b: 100 * (b - a * a) * (b - a * a) + (1 - a) * (1 - a))
    return F.aggregate(pairs, F.lit(0.0), lambda acc, v: acc + v)


def double_sum(x: Column) -> Column:
    zero = F.struct(F.lit(0.0).alias("s"), F.lit(0.0).alias("t"))
    return F.aggregate(x, zero, lambda acc, v: F.struct((acc.s + v).alias("s"), (acc.t + (acc.s + v) * (acc.s + v)).alias("t")), lambda acc: acc.t)


def plate(u: Column) -> Column:
    """Relative buckling strength from six uniforms."""
    make = {"normal": normal, "lognormal": lognormal}
    w, t, y, e, d, r = (make[kind](F.element_at(u, k + 1), mean, cv) for k, (_, kind, mean, cv) in enumerate(PLATE))
    slender = w / t * F.sqrt(y / e)
    return (2.1 / slender - 0.9 / (slender * slender)) * (1 - 0.75 * d / slender) * (1 - 2 * r * t / w)


def sphere_np(x: np.ndarray) -> np.ndarray:
    return (x * x).sum(axis=1)


def rosenbrock_np(x: np.ndarray) -> np.ndarray:
    a, b = x[:, :-1], x[:, 1:]
    return (100 * (b - a * a) ** 2 + (1 - a) ** 2).sum(axis=1)


def double_sum_np(x: np.ndarray) -> np.ndarray:
    return (np.cumsum(x, axis=1) ** 2).sum(axis=1)


def double_sum_normal_np(u: np.ndarray, mean: float = 0.0) -> np.ndarray:
    return double_sum_np(norm_ppf_np(u) + mean)


def plate_np(u: np.ndarray) -> np.ndarray:
    columns = []
    for k, (_, kind, mean, cv) in enumerate(PLATE):
        z = norm_ppf_np(u[:, k])
        mu, sigma = lognormal_shape(mean, cv)
        columns.append(mean + mean * cv * z if kind == "normal" else np.exp(mu + sigma * z))
    w, t, y, e, d, r = columns
    slender = w / t * np.sqrt(y / e)
    return (2.1 / slender - 0.9 / slender**2) * (1 - 0.75 * d / slender) * (1 - 2 * r * t / w)


class Trigonometric:
    """Least squares of random trigonometric sums: f = sum_i (A_i - B_i(x))**2, zero at a keyed place."""

    def __init__(self, n: int, *key: int) -> None:
        cell = np.arange(n)[:, None], np.arange(n)[None, :]
        self.a = 200 * rng.fast_uniform(*key, 51, *cell) - 100
        self.b = 200 * rng.fast_uniform(*key, 52, *cell) - 100
        self.optimum = math.pi * (2 * rng.fast_uniform(*key, 53, np.arange(n)) - 1)
        self.target = self.sums(self.optimum[None, :])

    def sums(self, x: np.ndarray) -> np.ndarray:
        return np.sin(x) @ self.a.T + np.cos(x) @ self.b.T

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return ((self.target - self.sums(x)) ** 2).sum(axis=1)


#: The place of each objective's minimum, per axis, before it is shifted.
OPTIMA = {"sphere": 0.0, "rosenbrock": 1.0, "double_sum": 0.0}
OBJECTIVES_NP = {"sphere": sphere_np, "rosenbrock": rosenbrock_np, "double_sum": double_sum_np}


def shifted(name: str, n: int, *key: int):
    """Objective whose optimum (value 0) lies at a keyed uniform place of [-pi, pi]**n."""
    if name == "trigonometric":
        return Trigonometric(n, *key)
    place = math.pi * (2 * rng.fast_uniform(*key, 54, np.arange(n)) - 1)
    f, best = OBJECTIVES_NP[name], OPTIMA[name]
    return lambda x: f(x - place[None, :] + best)
