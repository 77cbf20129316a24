"""Points from table rows: scaled numeric columns, empirical quantiles and simple text features."""

from __future__ import annotations

from fractions import Fraction
from math import ceil

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.checkpoints import durable


def ranges(rows: DataFrame, columns: dict[str, Column]) -> dict[str, tuple[float, float]]:
    """(min, max) of every column in one pass; empty input gives (0, 1)."""
    found = rows.agg(*[f(c.cast("double")).alias(f"{p}_{n}") for n, c in columns.items() for f, p in ((F.min, "lo"), (F.max, "hi"))]).first()
    return {n: (0.0, 1.0) if found[f"lo_{n}"] is None else (found[f"lo_{n}"], found[f"hi_{n}"]) for n in columns}


def unit(c: Column, lo: float, hi: float) -> Column:
    """Scaled to [0, 1]; a constant column becomes 0; null stays null."""
    return (c.cast("double") - F.lit(lo)) / F.lit(hi - lo) if hi > lo else c.cast("double") * 0.0


def scaled_points(rows: DataFrame, point_id: Column, columns: dict[str, Column], bounds: dict[str, tuple[float, float]] | None = None) -> DataFrame:
    """(point_id, x): rows as points of the unit cube; rows with a null coordinate get a null x."""
    bounds = bounds or ranges(rows, columns)
    axes = [unit(c, *bounds[n]) for n, c in columns.items()]
    known = axes[0].isNotNull()
    for a in axes[1:]:
        known = known & a.isNotNull()
    return rows.select(point_id.alias("point_id"), F.when(known, F.array(*axes)).alias("x"))


def timestamp_axis(c: Column) -> Column:
    return F.unix_micros(c.cast("timestamp")).cast("double")


def embedding_prefix(c: Column, n: int) -> Column:
    """First n components, from [-1, 1] to [0, 1]."""
    return F.transform(F.slice(c, 1, n), lambda v: (v.cast("double") + 1) / 2)


#: Distinct values of a range that one task adds up.
RANGE_VALUES = 200_000


def quantiles(rows: DataFrame, column: str, probabilities: list[float], exact: bool = True) -> DataFrame:
    """(probability, value): the smallest value whose share of rows reaches each probability; null on no known value.

    Exact ones come from counts of distinct values, dealt to ranges of the order
    whose number grows with them: the counts of ranges say which holds a
    quantile, and only those are added up value by value. No task holds more
    than a range.
    """
    spark = rows.sparkSession
    if not exact:
        row = rows.agg(F.percentile_approx(column, probabilities, 1_000_000).alias("v"))
        return row.select(F.posexplode("v").alias("k", "value")).select(F.element_at(F.array(*[F.lit(p) for p in probabilities]), F.col("k") + 1).alias("probability"), "value")
    counts = durable(rows.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("value")).agg(F.count("*").alias("n")))
    ranged = durable(counts.repartitionByRange(max(1, -(-counts.count() // RANGE_VALUES)), "value").withColumn("range", F.spark_partition_id()))
    sums = sorted((r["range"], r["n"]) for r in ranged.groupBy("range").agg(F.sum("n").alias("n")).collect())
    total, wanted = sum(n for _, n in sums), []
    for p in probabilities:
        # the whole number of rows that reaches p, without rounding of p * total
        rank, before = max(1, ceil(Fraction(repr(p)) * total)), 0
        for at, n in sums:
            if before < rank <= before + n:
                wanted.append((p, at, rank - before))
            before += n
    asked = F.broadcast(spark.createDataFrame(wanted, "probability double, range int, rank long"))
    w = Window.partitionBy("range").orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    near = ranged.join(asked.select("range").distinct(), "range", "left_semi").withColumn("upto", F.sum("n").over(w))
    found = near.join(asked, "range").where((F.col("upto") >= F.col("rank")) & (F.col("upto") - F.col("n") < F.col("rank"))).select("probability", "value")
    every = spark.createDataFrame([(p,) for p in probabilities], "probability double")
    return every.join(F.broadcast(found.dropDuplicates(["probability"])), "probability", "left")


def word_count(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^ \t\n\r]+"))
