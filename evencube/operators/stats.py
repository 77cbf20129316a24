"""Spread of estimates, medians and means with intervals, contests and non-dominated methods."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng


def estimate_spread(estimates: DataFrame, keys: list[str], value: str = "estimate") -> DataFrame:
    """Mean, standard deviation (sample), skewness and number of replicated estimates per key."""
    v = F.col(value)
    return estimates.groupBy(*keys).agg(F.count("*").alias("reps"), F.avg(v).alias("mean"), F.stddev_samp(v).alias("sd"), F.skewness(v).alias("skewness"))


def median_ranks(count: int) -> tuple[int, int]:
    """One-based ranks of a 95 % interval for the median from the binomial distribution (normal approximation)."""
    half = 1.96 * math.sqrt(count) / 2
    return max(1, math.floor(count / 2 - half)), min(count, math.ceil(count / 2 + half) + 1)


def median_ci(rows: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Per key: n, lower, median and upper, the outer ones by order statistics (exact percentiles, mergeable)."""
    sizes = rows.where(F.col(value).isNotNull()).groupBy(*keys).agg(F.count("*").alias("n"), F.expr(f"percentile(`{value}`, 0.5)").alias("median"))
    n = F.col("n").cast("double")
    low = F.greatest(F.lit(1), F.floor(n / 2 - 1.96 * F.sqrt(n) / 2))
    high = F.least(F.col("n"), F.ceil(n / 2 + 1.96 * F.sqrt(n) / 2) + 1)
    ranked = rows.where(F.col(value).isNotNull()).groupBy(*keys, F.col(value).alias("v_")).agg(F.count("*").alias("c_"))
    upto = ranked.withColumn("upto_", F.sum("c_").over(Window.partitionBy(*keys).orderBy("v_")))
    picked = upto.join(F.broadcast(sizes.withColumn("lo_", low).withColumn("hi_", high)), keys)
    ends = picked.groupBy(*keys).agg(F.min(F.when(F.col("upto_") >= F.col("lo_"), F.col("v_"))).alias("lower"), F.min(F.when(F.col("upto_") >= F.col("hi_"), F.col("v_"))).alias("upper"))
    return sizes.join(ends, keys).select(*keys, "n", "lower", "median", "upper")


def poisson_weight(u: Column, most: int = 8) -> Column:
    """Poisson(1) number of a uniform: how often a row is drawn in a bootstrap sample."""
    total, out = 0.0, F.lit(most)
    cuts = []
    for k in range(most):
        total += math.exp(-1) / math.factorial(k)
        cuts.append(total)
    for k in reversed(range(most)):
        out = F.when(u < cuts[k], F.lit(k)).otherwise(out)
    return out


def bootstrap_means(rows: DataFrame, keys: list[str], row_id: Column, value: str, samples: int, seed: int = 0) -> DataFrame:
    """(keys, sample, mean): weighted means under keyed Poisson(1) weights; no row is moved to be drawn."""
    drawn = rows.where(F.col(value).isNotNull()).select(*keys, row_id.alias("id_"), F.col(value).alias("v_"), F.explode(F.sequence(F.lit(0), F.lit(samples - 1))).alias("sample"))
    w = poisson_weight(rng.uniform(seed, "boot", F.col("id_"), F.col("sample")))
    return drawn.withColumn("w_", w).groupBy(*keys, "sample").agg((F.sum(F.col("w_") * F.col("v_")) / F.sum("w_")).alias("mean"))


def bootstrap_ci(rows: DataFrame, keys: list[str], row_id: Column, value: str, samples: int = 1000, seed: int = 0) -> DataFrame:
    """Per key: lower and upper 2.5 % points of the bootstrapped mean."""
    means = bootstrap_means(rows, keys, row_id, value, samples, seed)
    return means.groupBy(*keys).agg(F.expr("percentile(mean, 0.025)").alias("lower"), F.expr("percentile(mean, 0.975)").alias("upper"))


def contest(rows: DataFrame, keys: list[str], a: str, b: str, tie: float = 1e-9) -> DataFrame:
    """Per key: how often a is smaller than b, equal within ``tie``, larger."""
    gap = F.col(a) - F.col(b)
    n = lambda cond: F.sum(cond.cast("long"))
    return rows.groupBy(*keys).agg(n(gap < -tie).alias("wins"), n(F.abs(gap) <= tie).alias("ties"), n(gap > tie).alias("losses"))


def pareto_front(rows: DataFrame, method: str, a: str, b: str) -> DataFrame:
    """Rows that no other row beats in one measure without being worse in the other (smaller is better).

    A running minimum over the first measure replaces the self-join.
    """
    by = rows.groupBy(a).agg(F.min(b).alias("best_"))
    earlier = F.min("best_").over(Window.orderBy(a).rowsBetween(Window.unboundedPreceding, -1))
    front = by.withColumn("earlier_", earlier).where(F.col("earlier_").isNull() | (F.col("best_") < F.col("earlier_")))
    return rows.join(front.select(F.col(a).alias("a_"), "best_"), (F.col(a) == F.col("a_")) & (F.col(b) == F.col("best_")), "left_semi").select(method, a, b)


def correlations(pairs: DataFrame, by: str, a: str, b: str) -> DataFrame:
    return pairs.groupBy(by).agg(F.corr(a, b).alias("corr"))
