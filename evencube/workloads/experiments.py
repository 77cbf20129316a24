"""The experiments in their cube form: replicated designs, measured inside tasks.

One row of a small frame stands for one replication; tasks build the design
with NumPy, measure it and return numbers, so thousands of replications run in
parallel and only results travel. Every random number is keyed by experiment,
replication and place, so a repeated task repeats its rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..functions import objectives
from ..operators import covering, designs, discrepancy, fitted, latin, picking, stats, strata
from ..operators.draws import draw_np
from ..plans import planner
from ..sources.tables import read

SEED = 20_240


# designs by name


def block_sizes(text: str) -> list[int]:
    """``2^50`` or ``2^2.1^2`` as a list of block sizes."""
    return [int(size) for part in text.split(".") for size, times in [(part.split("^") + ["1"])[:2]] for _ in range(int(times))]


def _strata_np(count: int, n: int, *key: int, avoid_odd: bool = True) -> tuple[np.ndarray, np.ndarray]:
    return strata.bsplit_np(count, n, avoid_odd, mode="keyed", seed=int(rng.fast_key(*key, 61) >> np.uint64(33)))


def make_design(method: str, count: int, n: int, generators: dict[str, int], *key: int) -> np.ndarray:
    """Points of a design. Names: a method, then after a colon block sizes (padded) or draws per point (bsplit)."""
    name, _, option = method.partition(":")
    if name == "srs":
        return designs.srs_np(count, n, *key)
    if name == "lhs":
        return designs.lhs_np(count, n, *key)
    if name == "radinv":
        return designs.radinv_np(count, n, int(rng.fast_key(*key, 62) >> np.uint64(33)))
    if name in ("power_lattice", "power_lattice_latin"):
        return designs.lattice_np(count, n, generators[name], rng.fast_uniform(*key, 63, np.arange(n)))
    if name == "grid_centre":
        lo, hi = strata.grid_np(planner.integer_root(count, n), n)
        return (lo + hi) / 2
    if name == "grid_jitter":
        return draw_np(*strata.grid_np(planner.integer_root(count, n), n), 1, *key)
    if name == "bsplit":
        return draw_np(*_strata_np(count, n, *key), None if option == "inf" else int(option or 1), *key)
    if name in ("bsplit_cog", "bsplit_match"):
        how = "cog" if name == "bsplit_cog" else (option or "random_greedy")
        lo, hi = _strata_np(count, n, *key)
        if name == "bsplit_match" and how == "cog":
            return latin.latin_np(lo, hi, "cog_matched", *key)
        return latin.latin_np(lo, hi, how, *key)
    if name in ("padded_grid", "padded_grid_latin"):
        return designs.padded_grid_np(count, block_sizes(option), name == "padded_grid_latin", *key)
    if name in ("padded_bsplit", "padded_bsplit_cog", "padded_bsplit_match"):
        columns = []
        for b, size in enumerate(block_sizes(option)):
            x = make_design(name.removeprefix("padded_"), count, size, generators, *key, 64, b)
            columns.append(x[designs.shuffle_np(count, *key, 65, b)])
        return np.concatenate(columns, axis=1)
    raise ValueError(f"unknown design {method!r}")


def generators_for(spark: SparkSession, methods: Iterable[str], count: int, n: int, candidates: int | str = 30, seed: int = SEED) -> dict[str, int]:
    """Lattice generators of the largest separation among the candidates, found once per size."""
    wanted = {m for m in methods if m.startswith("power_lattice")}
    return {m: designs.best_generator(spark, count, n, candidates, seed, latin=m.endswith("latin")) for m in wanted}


def replicate(spark: SparkSession, jobs: Sequence[tuple], schema: str, work: Callable[..., list[tuple]], out: str) -> DataFrame:
    """Runs ``work(*job)`` for every job row in parallel tasks; jobs differ in cost, so they are dealt in small parts."""
    frame = spark.createDataFrame(list(jobs), schema)
    parts = min(len(jobs), 8 * spark.sparkContext.defaultParallelism) or 1
    names = [f.split()[0] for f in out.split(", ")]

    def run(batches):
        for pdf in batches:
            for row in pdf.itertuples(index=False):
                yield pd.DataFrame(work(*row), columns=names)

    return frame.repartition(parts, *frame.columns).mapInPandas(run, out)


# integration


HUNDRED = ("srs", "lhs", "radinv", "power_lattice_latin", "padded_grid:2^50", "padded_grid:4^25", "padded_grid_latin:2^50", "padded_grid_latin:4^25", "bsplit", "bsplit_cog", "bsplit_match:cog", "padded_bsplit_cog:2^50", "padded_bsplit_cog:4^25", "padded_bsplit_match:2^50", "padded_bsplit_match:4^25")
PLATE = ("srs", "lhs", "radinv", "power_lattice_latin", "padded_grid:2^3", "padded_grid:2^2.1^2", "padded_grid:4.1^2", "padded_grid_latin:2^3", "padded_grid_latin:2^2.1^2", "padded_grid_latin:4.1^2", "bsplit", "bsplit_cog", "bsplit_match")

INTEGRANDS: dict[str, dict[str, Callable[[np.ndarray], np.ndarray]]] = {
    "plate": {"plate": objectives.plate_np},
    "hundred": {
        "rosenbrock": objectives.rosenbrock_np,
        "double_sum_0": lambda u: objectives.double_sum_normal_np(u, 0.0),
        "double_sum_1": lambda u: objectives.double_sum_normal_np(u, 1.0),
    },
}


def integration_estimates(spark: SparkSession, which: str, reps: int, count: int = 625, methods: Sequence[str] | None = None) -> DataFrame:
    """(method, integrand, rep, estimate): mean of the integrand over each replicated design."""
    n, methods = (6, methods or PLATE) if which == "plate" else (100, methods or HUNDRED)
    generators = generators_for(spark, methods, count, n, "all")

    def work(method: str, rep: int) -> list[tuple]:
        x = make_design(method, count, n, generators, SEED, 1, rep)
        return [(method, name, rep, float(f(x).mean())) for name, f in INTEGRANDS[which].items()]

    jobs = [(m, r) for r in range(reps) for m in methods]
    return replicate(spark, jobs, "method string, rep int", work, "method string, integrand string, rep int, estimate double")


def integration_spread(spark: SparkSession, which: str, reps: int, count: int = 625, methods: Sequence[str] | None = None) -> DataFrame:
    """Mean and spread of the estimates per method and integrand."""
    return stats.estimate_spread(integration_estimates(spark, which, reps, count, methods), ["method", "integrand"])


# measures


MEASURED = ("srs", "lhs", "radinv", "power_lattice", "power_lattice_latin", "grid_centre", "bsplit:1", "bsplit:2", "bsplit:8", "bsplit:inf", "bsplit_cog")


#: Probes of the lower bound: ten for each point, or 20,000 for each axis.
PROBES: dict[str, Callable[[int, int], int]] = {"10N": lambda count, n: 10 * count, "1e4*2n": lambda count, n: 20_000 * n}


def measures_np(x: np.ndarray, probes: int, tries: int, *key: int, boxes: tuple[np.ndarray, np.ndarray] | None = None) -> dict[str, float]:
    """Discrepancy, lower and upper bound of the radius, and the radius where it is affordable; ``boxes`` are a design's own strata, else some are fitted."""
    n = x.shape[1]
    upper = covering.upper_np(x, *boxes) if boxes is not None else fitted.fitted_upper_np(x, tries, *key)
    out = {"discrepancy": math.sqrt(max(0.0, discrepancy.discrepancy_of(x))), "lower": covering.lower_np(x, probes, *key), "upper": upper}
    if planner.covering_method(len(x), n) == "exact":
        out["exact"] = covering.covering_exact_nd(x)
    return out


def measure_rows(spark: SparkSession, count: int, dims: Sequence[int], reps: int, methods: Sequence[str] = MEASURED, probes: str = "10N", tries: int = 10) -> DataFrame:
    """(method, n, count, rep, measure, value) of every replicated design; grids only where count is a power that fits.

    Two-way split designs are bounded by their own strata, others by fitted ones.
    """
    tables = {n: generators_for(spark, methods, count, n) for n in dims}
    jobs = [(m, n, r) for r in range(reps) for n in dims for m in methods if not m.startswith("grid") or planner.stratifier(count, n) == "grid"]

    def work(method: str, n: int, rep: int) -> list[tuple]:
        x = make_design(method, count, n, tables[n], SEED, 2, n, rep)
        # the points of a plain split design lie in the strata of the same key
        boxes = _strata_np(count, n, SEED, 2, n, rep) if method.startswith("bsplit:") else None
        return [(method, n, count, rep, k, v) for k, v in measures_np(x, PROBES[probes](count, n), tries, SEED, 3, n, rep, boxes=boxes).items()]

    return replicate(spark, jobs, "method string, n int, rep int", work, "method string, n int, count long, rep int, measure string, value double")


def measure_table(spark: SparkSession, count: int, dims: Sequence[int], reps: int, methods: Sequence[str] = MEASURED, probes: str = "10N", tries: int = 10) -> DataFrame:
    """Mean of every measure per method and dimension, with a flag for methods that no other beats in discrepancy and radius at once."""
    from pyspark.sql.window import Window

    rows = measure_rows(spark, count, dims, reps, methods, probes, tries)
    wide = rows.groupBy("n", "method").pivot("measure", ["discrepancy", "lower", "exact", "upper"]).agg(F.avg("value"))
    wide = wide.withColumn("radius", F.coalesce("exact", "upper"))
    best_before = F.min("radius").over(Window.partitionBy("n").orderBy("discrepancy").rowsBetween(Window.unboundedPreceding, -1))
    return wide.withColumn("front", F.coalesce(F.col("radius") < best_before, F.lit(True)))


def discrepancy_sweep(spark: SparkSession, dims: Sequence[int], sizes: Sequence[int], reps: int | None = None, methods: Sequence[str] = MEASURED, measure: str = "discrepancy", tries: int = 3) -> DataFrame:
    """Median discrepancy or covering radius with its 95 % interval per method, dimension and size.

    The radius is exact where ``planner.covering_method`` says so, else the upper
    bound by a design's own strata or by fitted ones.
    """
    if measure not in ("discrepancy", "radius"):
        raise ValueError("measure is discrepancy or radius")
    tables = {(n, c): generators_for(spark, methods, c, n) for n in dims for c in sizes}
    jobs = [(m, n, c, r) for n in dims for c in sizes for r in range(reps or max(1, 400 // n)) for m in methods if not m.startswith("grid") or planner.stratifier(c, n) == "grid"]

    def work(method: str, n: int, c: int, rep: int) -> list[tuple]:
        key = (SEED, 4, n, c, rep)
        x = make_design(method, c, n, tables[n, c], *key)
        if measure == "discrepancy":
            value = math.sqrt(max(0.0, discrepancy.discrepancy_of(x)))
        elif planner.covering_method(c, n) == "exact":
            value = covering.covering_exact_nd(x)
        else:
            value = covering.upper_np(x, *_strata_np(c, n, *key)) if method.startswith("bsplit:") else fitted.fitted_upper_np(x, tries, *key)
        return [(method, n, c, value)]

    rows = replicate(spark, jobs, "method string, n int, count int, rep int", work, "method string, n int, count int, value double")
    named = rows.withColumnRenamed("n", "dims").withColumnRenamed("count", "size")
    return stats.median_ci(named, ["method", "dims", "size"], "value")


# covering radius


def exact_radius(points: DataFrame, set_id: str, x: str = "x") -> DataFrame:
    """(set_id, radius): exact covering radius of many small sets in the unit cube, one task a set."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({set_id: [pdf[set_id].iloc[0]], "radius": [covering.covering_exact_nd(np.stack(pdf[x].to_numpy()))]})

    kind = points.schema[set_id].dataType.simpleString()
    return points.select(set_id, x).groupBy(set_id).applyInPandas(run, f"{set_id} {kind}, radius double")


def radius_bounds(spark: SparkSession, dims: Sequence[int], sizes: Sequence[int], probes_per_point: int = 10) -> DataFrame:
    """(dims, count, lower, exact, upper, normalized) of stratum centres with the even-preferring rule."""

    def work(n: int, count: int) -> list[tuple]:
        lo, hi = _strata_np(count, n, SEED, 5, n, count)
        x = (lo + hi) / 2
        exact = covering.covering_exact_nd(x)
        return [(n, count, covering.lower_np(x, probes_per_point * count, SEED, 6, n, count), exact, covering.upper_np(x, lo, hi), exact / covering.covering_floor(count, n))]

    jobs = [(n, c) for n in dims for c in sizes]
    return replicate(spark, jobs, "dims int, count int", work, "dims int, count int, lower double, exact double, upper double, normalized double")


def radius_bounds_of_rows(points: DataFrame, n: int, sizes: Sequence[int], seed: int) -> DataFrame:
    """(dims, count, exact, upper) of the rows nearest to stratum centres, for every size; random (keyed) splits with the even-preferring rule."""
    boxes = {c: strata.tree_boxes_np(c, n, mode="keyed", seed=seed) for c in sizes}

    def run(picked: pd.DataFrame) -> pd.DataFrame:
        picked = picked.sort_values("stratum_id")
        x, c = np.stack(picked["x"].to_numpy()), int(picked["count"].iloc[0])
        upper = covering.upper_in_boxes_np(x, picked["stratum_id"].to_numpy(), *boxes[c])
        return pd.DataFrame({"dims": [n], "count": [c], "exact": [covering.covering_exact_nd(x)], "upper": [upper]})

    return picking.nearest_to_centres(points, n, boxes).groupBy("count").applyInPandas(run, "dims int, count int, exact double, upper double")


def rule_measures(spark: SparkSession, dims: Sequence[int], sizes: Iterable[int], exact_dims: int = 2, mode: str = "keyed") -> DataFrame:
    """(dims, count, with_rule, without_rule): radius of stratum centres, exact up to ``exact_dims`` axes, else the upper bound.

    Random (keyed) splits as published, each side with draws of its own; or fixed ones.
    """

    def work(n: int, count: int) -> list[tuple]:
        found = []
        for rule in (True, False):
            lo, hi = _strata_np(count, n, SEED, 9, n, count, int(rule), avoid_odd=rule) if mode == "keyed" else strata.bsplit_np(count, n, rule)
            x = (lo + hi) / 2
            found.append(covering.covering_exact_nd(x) if n <= exact_dims else covering.upper_np(x, lo, hi))
        return [(n, count, *found)]

    jobs = [(n, c) for n in dims for c in sizes]
    return replicate(spark, jobs, "dims int, count int", work, "dims int, count int, with_rule double, without_rule double")


def rule_table(spark: SparkSession, dims: Sequence[int], sizes: Iterable[int], exact_dims: int = 2, mode: str = "keyed", tie: float = 0.0) -> DataFrame:
    """(dims, wins, ties, losses) of the rule; as published, ties are equal to the last bit unless ``tie`` says otherwise."""
    return stats.contest(rule_measures(spark, dims, list(sizes), exact_dims, mode), ["dims"], "with_rule", "without_rule", tie)


def oversample_select(spark: SparkSession, count: int, n: int, factor: int = 20) -> DataFrame:
    """Selection from uniform points beside direct strata: share of points within 5 % of the cube's faces (expected 1 - 0.9**n)."""
    cloud = designs.srs(spark, factor * count, n, seed=3)
    picked = fitted.select_uniform_subset(cloud, count, n)
    direct = strata.bsplit_strata(spark, count, n, mode="keyed", seed=3)
    from ..operators.draws import draw

    near = F.exists("x", lambda v: (v < 0.05) | (v > 0.95)).cast("double")
    one = lambda df, name: df.agg(F.lit(name).alias("method"), F.count("*").alias("points"), F.avg(near).alias("near_faces"))
    both = one(picked, "select").unionByName(one(draw(direct, 1, seed=3), "bsplit"))
    return both.withColumn("expected", F.lit(1 - 0.9**n))


# optimization


OPTIMIZERS = ("srs", "lhs", "radinv", "power_lattice_latin", "bsplit:1", "bsplit:inf", "bsplit_cog")
OBJECTIVES = ("sphere", "rosenbrock", "double_sum", "trigonometric")


def optimum_gap_rows(spark: SparkSession, dims: Sequence[int], reps: int, methods: Sequence[str] = OPTIMIZERS, candidates: int = 1000) -> DataFrame:
    """(method, n, objective, rep, gap): best of 50 n points against a keyed optimum in [-pi, pi]**n."""
    tables = {n: generators_for(spark, methods, 50 * n, n, candidates) for n in dims}

    def work(method: str, n: int, rep: int) -> list[tuple]:
        x = math.pi * (2 * make_design(method, 50 * n, n, tables[n], SEED, 7, n, rep) - 1)
        return [(method, n, name, rep, float(objectives.shifted(name, n, SEED, 8, n, rep, k)(x).min())) for k, name in enumerate(OBJECTIVES)]

    jobs = [(m, n, r) for n in dims for r in range(reps) for m in methods]
    return replicate(spark, jobs, "method string, n int, rep int", work, "method string, n int, objective string, rep int, gap double")


def optimum_gaps(spark: SparkSession, dims: Sequence[int], reps: int, methods: Sequence[str] = OPTIMIZERS, samples: int = 200) -> DataFrame:
    """Mean gap with a bootstrapped 95 % interval, and the median, per method, dimension and objective."""
    rows = optimum_gap_rows(spark, dims, reps, methods)
    keys = ["method", "n", "objective"]
    middle = rows.groupBy(*keys).agg(F.avg("gap").alias("mean"), F.expr("percentile(gap, 0.5)").alias("median"))
    return middle.join(stats.bootstrap_ci(rows, keys, F.col("rep"), "gap", samples, SEED), keys)


# tables


def inverse_marginals(spark: SparkSession, sf_dir: str, points: DataFrame, marginals: Sequence[tuple[str, str]]) -> DataFrame:
    """``points`` with product: each coordinate through the empirical inverse distribution of a table's column, over the column's mean, multiplied.

    A uniform u stands for the row of rank ceil(u n): ranks are found without a
    global sort task and met by the (design-sized) wanted ranks.
    """
    out = points.withColumn("product", F.lit(1.0))
    for d, (table, column) in enumerate(marginals, 1):
        rows = read(spark, sf_dir, table).where(F.col(column).isNotNull()).select(F.col(column).cast("double").alias("v"))
        size = rows.agg(F.count("*").alias("n"), F.avg("v").alias("mean")).first()
        ranked = latin.global_rank(rows.withColumn("one", F.lit(0)), "one", ["v"]).select("v", "rank")
        wanted = F.greatest(F.lit(1), F.ceil(F.element_at("x", d) * size.n - 1e-9)).cast("long") - 1
        looked = points.select(wanted.alias("rank")).distinct()
        values = ranked.join(F.broadcast(looked), "rank").withColumnRenamed("rank", f"rank{d}").withColumnRenamed("v", f"v{d}")
        out = out.withColumn(f"rank{d}", wanted).join(F.broadcast(values), f"rank{d}").withColumn("product", F.col("product") * F.col(f"v{d}") / F.lit(size.mean)).drop(f"rank{d}", f"v{d}")
    return out
