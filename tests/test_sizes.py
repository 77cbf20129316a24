"""Queries whose one task or all pairs did not hold at size: exact results from ranges and blocks."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from evencube.functions import tables as tf


def test_quantiles_over_several_ranges(spark, monkeypatch):
    monkeypatch.setattr(tf, "RANGE_VALUES", 7)
    r = np.random.default_rng(2)
    v = [float(a) for a in np.r_[r.integers(0, 40, 900) / 8, np.full(300, 1.5), -0.0, math.inf]]
    rows = spark.createDataFrame([(a,) for a in v] + [(None,)] * 5, "v double")
    asked = [0.0, 0.001, 0.1, 0.5, 0.7, 0.99, 1.0]
    got = tf.quantiles(rows, "v", asked)
    values, order = {x.probability: x.value for x in got.collect()}, np.sort(v)
    assert values == {p: order[max(1, math.ceil(round(p * 1000) * len(v) / 1000)) - 1] for p in asked}
    # one task no longer gathers all values: the windows run over ranges
    assert "percentile_disc" not in got._jdf.queryExecution().toString()
    none = tf.quantiles(rows.where("v is null"), "v", [0.5, 0.9]).collect()
    assert [(x.probability, x.value) for x in sorted(none)] == [(0.5, None), (0.9, None)]


@pytest.mark.parametrize("n", [1, 2, 3, 4])
def test_discrepancy_in_blocks_is_that_of_all_pairs(spark, monkeypatch, n):
    from evencube.operators import discrepancy

    monkeypatch.setattr(discrepancy, "TILED", 50)
    monkeypatch.setattr(discrepancy, "BLOCK", 60)
    monkeypatch.setattr(discrepancy, "_pair_sums", None)  # no tile of pairs is formed
    r = np.random.default_rng(n)
    x = r.random((400, n))
    x[:, 0] = np.round(x[:, 0] * 3) / 3 if n > 1 else x[:, 0]
    x = np.r_[x, x[:50], np.ones((1, n)), np.zeros((1, n))]
    rows = spark.createDataFrame([(k, [float(a) for a in p]) for k, p in enumerate(x)] + [(999, None)], "point_id long, x array<double>")
    row = discrepancy.discrepancy(rows.repartition(3), n).first()
    kernel = np.ones((len(x), len(x)))
    for d in range(n):
        p, q = x[:, d, None], x[None, :, d]
        kernel *= np.minimum(p, q) * (1 - np.maximum(p, q))
    want = kernel.mean() - 2.0 ** (1 - n) * (x * (1 - x)).prod(axis=1).mean() + 12.0**-n
    assert row["count"] == len(x) and row.discrepancy_sq == pytest.approx(want, abs=1e-13)


@pytest.mark.parametrize("n", [2, 5])
def test_equal_points_form_no_pairs_of_rows(spark, monkeypatch, n):
    from evencube.operators import discrepancy

    seen, tiles = spark.sparkContext.accumulator(0), discrepancy._pair_sums

    def counted(a, b, *w):
        seen.add(len(a) * len(b))
        return tiles(a, b, *w)

    monkeypatch.setattr(discrepancy, "TILE", 8)
    monkeypatch.setattr(discrepancy, "_pair_sums", counted)
    x = np.random.default_rng(n).random((20, n))
    times = np.arange(1, 21)
    rows = spark.createDataFrame([([float(a) for a in p], int(t)) for p, t in zip(x, times)], "x array<double>, t int")
    row = discrepancy.discrepancy(rows.selectExpr("explode(array_repeat(x, t)) AS x").repartition(3), n).first()
    # 20 points in tiles, not 210 rows
    assert row["count"] == times.sum() == 210 and 0 < seen.value <= 400
    assert row.discrepancy_sq == pytest.approx(discrepancy.discrepancy_np(np.repeat(x, times, axis=0)), abs=1e-13)
