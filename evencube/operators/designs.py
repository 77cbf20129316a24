"""Competing designs: uniform, Latin hypercube, radical inverse, rank-1 lattices, grids and padded blocks.

All are projections of ``spark.range``: permutations are keyed bijections, so
no design needs a sort, a join or an exchange. The NumPy twins serve
experiments with thousands of replications per task.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..plans import planner

#: Points of a lattice that are stepped through at once.
BLOCK = 1 << 18


def _frame(spark: SparkSession, count: int, axes: Sequence[Column]) -> DataFrame:
    return spark.range(count).select(F.col("id").alias("point_id"), F.array(*axes).alias("x"))


def primes(n: int) -> list[int]:
    found: list[int] = []
    k = 2
    while len(found) < n:
        if all(k % p for p in found if p * p <= k):
            found.append(k)
        k += 1
    return found


def srs(spark: SparkSession, count: int, n: int, seed: int = 0) -> DataFrame:
    """Independent uniform points."""
    return _frame(spark, count, [rng.uniform(seed, "srs", F.col("id"), d) for d in range(n)])


def lhs(spark: SparkSession, count: int, n: int, seed: int = 0, centred: bool = False) -> DataFrame:
    """One point per 1/count slab of every axis."""
    axes = []
    for d in range(n):
        u = F.lit(0.5) if centred else rng.uniform(seed, "lhs", F.col("id"), d)
        axes.append((rng.permute(F.col("id"), count, seed, d) + u) / F.lit(float(count)))
    return _frame(spark, count, axes)


def digit_orders(base: int, seed: int, permuted: bool) -> list[int]:
    """Order of the digits of one base; zero stays."""
    rest = list(range(1, base))
    if permuted:
        rest.sort(key=lambda k: rng.uniform_py(seed, "digits", base, k))
    return [0, *rest]


def radinv(spark: SparkSession, count: int, n: int, seed: int = 0, start: int = 1, permuted: bool = True) -> DataFrame:
    """Radical inverses of start.. in the first n primes, digits permuted."""
    axes = []
    for base in primes(n):
        order = F.array(*[F.lit(v).cast("double") for v in digit_orders(base, seed, permuted)])
        levels = max(1, math.ceil(math.log(count + start + 1) / math.log(base)))
        state = F.struct((F.col("id") + start).alias("rest"), F.lit(1.0 / base).alias("unit"), F.lit(0.0).alias("value"))
        done = F.aggregate(
            F.sequence(F.lit(1), F.lit(levels)),
            state,
            lambda s, _: F.struct(
                F.floor(s.rest / base).alias("rest"),
                (s.unit / base).alias("unit"),
                (s.value + s.unit * F.element_at(order, (F.pmod(s.rest, F.lit(base)) + 1).cast("int"))).alias("value"),
            ),
        )
        axes.append(done.value)
    return _frame(spark, count, axes)


def radinv_np(count: int, n: int, seed: int, start: int = 1, permuted: bool = True) -> np.ndarray:
    out = np.zeros((count, n))
    for d, base in enumerate(primes(n)):
        order = np.array(digit_orders(base, seed, permuted), float)
        rest, unit = np.arange(start, start + count), 1.0 / base
        while rest.any():
            out[:, d] += unit * order[rest % base]
            rest, unit = rest // base, unit / base
    return out


def generator_powers(a: int, count: int, n: int) -> list[int]:
    out, z = [], 1
    for _ in range(n):
        out.append(z)
        z = z * a % count
    return out


def lattice_separation(a: int, count: int, n: int) -> float:
    """Smallest distance on the torus between lattice points; differences are lattice points, so those to 0 suffice."""
    z, best = np.array(generator_powers(a, count, n), object), math.inf
    z = z.astype(np.int64) if count < 1 << 31 else z
    for start in range(1, count // 2 + 1, BLOCK):  # i and -i are equally far
        i = np.arange(start, min(start + BLOCK, count // 2 + 1))[:, None]
        r = (i * z[None, :] % count).astype(np.float64) / count
        best = min(best, float(np.sqrt((np.minimum(r, 1 - r) ** 2).sum(axis=1).min())))
    return best if count > 1 else 0.0


def lattice_candidates(count: int, candidates: int | str, seed: int, latin: bool) -> list[int]:
    """Generators to try: all, or a keyed choice; latin ones are coprime to count."""
    if candidates == "all" or candidates >= count:
        return [a for a in range(1, max(2, count)) if not latin or math.gcd(a, count) == 1]
    out, k = [], 0
    while len(out) < candidates and k < 1000 * candidates:
        a = 1 + int(rng.uniform_py(seed, "generator", k) * (count - 1))
        k += 1
        if a not in out and (not latin or math.gcd(a, count) == 1):
            out.append(a)
    return out


def best_generator(spark: SparkSession, count: int, n: int, candidates: int | str | DataFrame = 30, seed: int = 0, latin: bool = False) -> int:
    """The candidate of largest separation; ties to the smallest. Candidates, or rows (a) of a table, are judged in parallel tasks."""
    if isinstance(candidates, DataFrame):
        return separations(candidates, count, n).orderBy(F.desc(F.round("separation", 12)), "a").first().a
    tried = lattice_candidates(count, candidates, seed, latin)
    if len(tried) * count <= 1 << 22:
        return min(tried, key=lambda a: (-round(lattice_separation(a, count, n), 12), a))
    frame = spark.createDataFrame([(a,) for a in tried], "a long").repartition(min(len(tried), 4 * spark.sparkContext.defaultParallelism), "a")
    measured = separations(frame, count, n)
    return measured.orderBy(F.desc(F.round("separation", 12)), "a").first().a


def separations(generators: DataFrame, count: int, n: int) -> DataFrame:
    """(a, separation) of every generator in ``generators`` (a)."""

    def run(batches):
        for pdf in batches:
            yield pdf.assign(separation=[lattice_separation(int(a), count, n) for a in pdf["a"]])

    return generators.mapInPandas(run, "a long, separation double")


def power_lattice(spark: SparkSession, count: int, n: int, a: int | None = None, candidates: int | str = 30, seed: int = 0, latin: bool = False, shift: bool = True) -> DataFrame:
    """Rank-1 lattice with generator (1, a, a**2, ...), shifted as a whole; products beyond 2**63 use decimals."""
    a = best_generator(spark, count, n, candidates, seed, latin) if a is None else a
    axes = []
    for d, z in enumerate(generator_powers(a, count, n)):
        i = F.col("id") if count < 1 << 31 else F.col("id").cast("decimal(38,0)")
        step = F.pmod(i * F.lit(z).cast("long" if count < 1 << 31 else "decimal(38,0)"), F.lit(count)).cast("double") / F.lit(float(count))
        axes.append(F.pmod(step + F.lit(rng.uniform_py(seed, "shift", d)), F.lit(1.0)) if shift else step)
    return _frame(spark, count, axes)


def lattice_np(count: int, n: int, a: int, shift: np.ndarray | None = None) -> np.ndarray:
    x = np.arange(count)[:, None] * np.array(generator_powers(a, count, n))[None, :] % count / count
    return x if shift is None else (x + shift) % 1.0


def grid_centre(spark: SparkSession, k: int, n: int) -> DataFrame:
    from .draws import draw
    from .strata import grid_strata

    return draw(grid_strata(spark, [k] * n), b=None).select("point_id", "x")


def grid_jitter(spark: SparkSession, k: int, n: int, seed: int = 0) -> DataFrame:
    from .draws import draw
    from .strata import grid_strata

    return draw(grid_strata(spark, [k] * n), 1, seed).select("point_id", "x")


def grid_latin_axis(i: Column, k: int, n: int, d: int, seed: int, block: int = 0) -> tuple[Column, Column]:
    """(cell digit, 1/N bin) along axis d of the Latin grid point in cell i: the k**(n-1) cells of a slab share its bins by a keyed bijection."""
    digit = F.pmod(F.floor(i / k**d), F.lit(k))
    # the cell's number among those of its slab: its digits without this one
    low, high = F.pmod(i, F.lit(k**d)), F.floor(i / k ** (d + 1))
    within = (high * k**d + low).cast("long")
    size = k ** (n - 1)
    shifted = F.pmod(rng.permute(within, size, seed, 1000 + 50 * block + d) + F.floor(rng.uniform(seed, "slab", digit, block, d) * size), F.lit(size))
    return digit, digit * size + shifted


def grid_latin(spark: SparkSession, k: int, n: int, seed: int = 0) -> DataFrame:
    """Latin equal grid: one point per cell and per 1/k**n bin of every axis."""
    axes = []
    for d in range(n):
        _, bin_ = grid_latin_axis(F.col("id"), k, n, d, seed)
        axes.append((bin_ + rng.uniform(seed, "jitter", F.col("id"), 0, d)) / F.lit(float(k**n)))
    return _frame(spark, k**n, axes)


def padded_grid(spark: SparkSession, count: int, blocks: Sequence[int], latin: bool = False, seed: int = 0) -> DataFrame:
    """Grid designs of the given block sizes, glued column by column under keyed row orders; no join."""
    axes, cells = [], {}
    for b, size in enumerate(blocks):
        k = planner.integer_root(count, size)
        if k**size != count:
            raise ValueError(f"{count} points do not fill a grid of {size} dimensions")
        cells[f"cell{b}"] = rng.permute(F.col("id"), count, seed, 100 + b)
        cell = F.col(f"cell{b}")
        for d in range(size):
            u = rng.uniform(seed, "jitter", F.col("id"), b, d)
            if latin:
                _, bin_ = grid_latin_axis(cell, k, size, d, seed, b)
                axes.append((bin_ + u) / F.lit(float(count)))
            else:
                axes.append((F.pmod(F.floor(cell / k**d), F.lit(k)) + u) / F.lit(float(k)))
    return spark.range(count).withColumns(cells).select(F.col("id").alias("point_id"), F.array(*axes).alias("x"))


def padded_designs(parts: Sequence[DataFrame], count: int, seed: int = 0) -> DataFrame:
    """Block designs (point_id, x) of ``count`` points glued under keyed row orders by equi-joins on the permuted number."""
    out = None
    for b, part in enumerate(parts):
        placed = part.select(rng.permute(F.col("point_id"), count, seed, 100 + b).alias("point_id"), F.col("x").alias(f"x{b}"))
        out = placed if out is None else out.join(placed, "point_id")
    return out.select("point_id", F.concat(*[F.col(f"x{b}") for b in range(len(parts))]).alias("x"))


# NumPy twins for experiments; keys are (seed, rep) pairs


def srs_np(count: int, n: int, *key: int) -> np.ndarray:
    return rng.fast_uniform(*key, 11, np.arange(count)[:, None], np.arange(n)[None, :])


def shuffle_np(count: int, *key: int) -> np.ndarray:
    return np.argsort(rng.fast_key(*key, np.arange(count)), kind="stable")


def lhs_np(count: int, n: int, *key: int) -> np.ndarray:
    bins = np.stack([shuffle_np(count, *key, 12, d) for d in range(n)], axis=1)
    return (bins + srs_np(count, n, *key, 13)) / count


def padded_grid_np(count: int, blocks: Sequence[int], latin: bool, *key: int) -> np.ndarray:
    columns = []
    for b, size in enumerate(blocks):
        k = planner.integer_root(count, size)
        if k**size != count:
            raise ValueError(f"{count} points do not fill a grid of {size} dimensions")
        cell = shuffle_np(count, *key, 14, b)
        for d in range(size):
            digit = cell // k**d % k
            u = rng.fast_uniform(*key, 15, b, d, np.arange(count))
            if latin:
                # ranks of keyed numbers inside each slab are its bins
                order = np.lexsort((rng.fast_key(*key, 16, b, d, cell), digit))
                bins = np.empty(count, np.int64)
                bins[order] = np.arange(count)
                columns.append((bins + u) / count)
            else:
                columns.append((digit + u) / k)
    return np.stack(columns, axis=1)
