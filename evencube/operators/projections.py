"""Quality of one-dimensional projections."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def projection_histogram(points: DataFrame, bins: int, x: str = "x") -> DataFrame:
    """(dim, bin, n): points per equal bin of every axis; values at 1 belong to the last bin."""
    rows = points.select(F.posexplode(x).alias("dim", "v"))
    bin_ = F.least(F.greatest(F.floor(F.col("v") * bins), F.lit(0)), F.lit(bins - 1)).cast("long")
    return rows.groupBy("dim", bin_.alias("bin")).agg(F.count("*").alias("n"))
