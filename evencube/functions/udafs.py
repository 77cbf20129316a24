"""Grouped measures as aggregate functions for DataFrames and SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..operators.discrepancy import discrepancy_of


def discrepancy_agg(x: Column) -> Column:
    """Squared discrepancy of each group's points (array column); a group must fit a task. Null points take no part."""

    @F.pandas_udf("double")
    def run(points: pd.Series) -> float:
        known = points.dropna()
        return discrepancy_of(np.stack(known.to_numpy())) if len(known) else float("nan")

    return run(x)


def register(spark: SparkSession) -> None:
    """``SELECT discrepancy(array(a, b)) FROM t GROUP BY g``."""

    @F.pandas_udf("double")
    def discrepancy(points: pd.Series) -> float:
        known = points.dropna()
        return discrepancy_of(np.stack(known.to_numpy())) if len(known) else float("nan")

    spark.udf.register("discrepancy", discrepancy)
