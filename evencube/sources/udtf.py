"""SQL surface: ``SELECT * FROM bsplit(144, 2)`` and scalar functions over boxes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from ..operators.strata import bsplit_np


class Bsplit:
    """Boxes of the fixed mode; the number of axes, a constant, sets the columns."""

    @staticmethod
    def analyze(count: AnalyzeArgument, dims: AnalyzeArgument) -> AnalyzeResult:
        if dims.value is None:
            raise ValueError("dims must be a constant")
        fields = [T.StructField("stratum_id", T.LongType())]
        fields += [T.StructField(f"{s}{d}", T.DoubleType()) for d in range(1, int(dims.value) + 1) for s in ("lo", "hi")]
        return AnalyzeResult(T.StructType(fields))

    def eval(self, count: int, dims: int):
        lo, hi = bsplit_np(int(count), int(dims))
        rows = np.stack([lo, hi], axis=2).reshape(len(lo), -1)
        for k, row in enumerate(rows.tolist()):
            yield (k, *row)


def register(spark: SparkSession) -> None:
    spark.udtf.register("bsplit", F.udtf(Bsplit))
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION corner_distance(x ARRAY<DOUBLE>, lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>) RETURNS DOUBLE "
        "RETURN sqrt(aggregate(zip_with(x, zip_with(lo, hi, (a, b) -> struct(a AS lo, b AS hi)), (v, s) -> greatest(v - s.lo, s.hi - v)), 0D, (acc, v) -> acc + v * v))"
    )
