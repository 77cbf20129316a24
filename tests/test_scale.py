"""Heavy ties, constant columns and large spaces: no task gets more than its share; results by brute force."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from evencube.operators import covering, fitted, latin, strata


def test_ranks_of_a_constant_column_are_split(spark, monkeypatch):
    monkeypatch.setattr(latin, "RANGE_ROWS", 500)
    rows = spark.range(4000).select(F.lit(0).alias("dim"), F.lit(1.5).alias("v"), F.col("id").alias("key"))
    seen, plain = [], latin.durable

    def watch(df):
        out = plain(df)
        seen.append(out.groupBy("range_").count().agg(F.max("count")).first()[0])
        return out

    monkeypatch.setattr(latin, "durable", watch)
    got = latin.global_rank(rows, "dim", ["v", "key"]).toPandas()
    assert (got["rank"] == got.key).all() and seen[0] <= 1500


def test_ranks_by_brute_force(spark, monkeypatch):
    monkeypatch.setattr(latin, "RANGE_ROWS", 100)
    r = np.random.default_rng(0)
    data = pd.DataFrame({"dim": r.integers(0, 3, 900), "v": r.integers(0, 7, 900) / 7, "key": np.arange(900)})
    want = data.sort_values(["dim", "v", "key"]).groupby("dim").cumcount()
    for got in (latin.global_rank(spark.createDataFrame(data), "dim", ["v", "key"]), latin.bucket_rank(spark.createDataFrame(data), "dim", ["v", "key"], 900)):
        assert (got.toPandas().set_index("key")["rank"].sort_index() == want.sort_index()).all()


@pytest.mark.parametrize("count,n", [(100, 2), (196, 3)])
def test_bucket_sort_gives_the_same_bins(spark, monkeypatch, count, n):
    boxes = strata.bsplit_strata(spark, count, n)
    one = {(r.stratum_id, r.dim): r.bin for r in latin.cog_bins(boxes, count).collect()}
    monkeypatch.setattr(latin, "RANGE_ROWS", 20)
    assert one == {(r.stratum_id, r.dim): r.bin for r in latin.cog_bins(boxes, count, rank="bucket").collect()}


def test_many_equal_points_share_a_box(spark, monkeypatch):
    """60,000 equal points and some others: large boxes are cut level by level, equal points end it."""
    monkeypatch.setattr(fitted, "LOCAL_POINTS", 1000)
    same = spark.range(60_000).select(F.col("id").alias("point_id"), F.array(F.lit(0.25), F.lit(0.75)).alias("x"))
    r = np.random.default_rng(3).random((200, 2))
    more = spark.createDataFrame([(100_000 + k, [float(a) for a in p]) for k, p in enumerate(r)], "point_id long, x array<double>")
    got = fitted.mean_gap_partition(same.unionByName(more), 2).cache()
    assert got.count() == 60_200
    boxes = got.select("lo", "hi", "x").distinct().toPandas()
    lo, hi, x = (np.stack(boxes[c]) for c in ("lo", "hi", "x"))
    assert len(boxes) == 201 and np.isclose((hi - lo).prod(axis=1).sum(), 1) and ((lo <= x) & (x <= hi)).all()


def test_level_cuts_agree_with_the_local_ones(spark, monkeypatch):
    monkeypatch.setattr(fitted, "LOCAL_POINTS", 20)
    x = np.random.default_rng(5).random((300, 1))
    got = fitted.mean_gap_partition(spark.createDataFrame([(k, [float(v[0])]) for k, v in enumerate(x)], "point_id long, x array<double>"), 1).toPandas().set_index("point_id").sort_index()
    lo, hi = fitted.mean_gap_np(x, np.zeros(1), np.ones(1))
    assert np.allclose(np.stack(got.lo), lo) and np.allclose(np.stack(got.hi), hi)


def test_a_large_space_is_sliced(spark, monkeypatch):
    monkeypatch.setattr(covering, "PLACES", 50)
    monkeypatch.setattr(covering, "BLOCK", 7)
    r = np.random.default_rng(1)
    p, x = r.random((400, 3)), r.random((30, 3))
    rows = lambda a, name: spark.createDataFrame([(k, [float(v) for v in q]) for k, q in enumerate(a)], f"{name} long, p array<double>")
    got = covering.nearest(rows(p, "probe_id"), rows(x, "point_id").withColumnRenamed("p", "x")).toPandas().set_index("probe_id").distance.sort_index()
    assert np.allclose(got, np.sqrt(((p[:, None] - x[None]) ** 2).sum(axis=2).min(axis=1)))


def test_picked_rows_stand_for_all(spark, small):
    """The queries over embeddings, by the local rule on whole tables."""
    from evencube.workloads import measure_queries  # noqa: F401
    from evencube.workloads.registry import QUERIES

    rows = pd.read_parquet(f"{small}/embeddings.parquet").sort_values("vec_id")
    full = np.stack(rows.embedding).astype(float)
    got = QUERIES["optimum_gap_emb"](spark, small).toPandas().set_index("dims")
    for n in (2, 4, 8, 16):
        x, f = (full[:, :n] + 1) / 2, ((full[:, :n] - 0.05) ** 2).sum(axis=1)
        picked = fitted.pick_np(x, min(50 * n, len(x)))
        assert got.loc[n, "picked_min"] == pytest.approx(f[picked].min(), abs=2e-6) and got.loc[n, "true_min"] == pytest.approx(f.min(), abs=2e-6)
    assert (got.loc[[16, 32, 64], "gap"] == 0).all()
    x = (full[:, :4] + 1) / 2
    picked = x[fitted.pick_np(x, 200)]
    want = np.sqrt(((x[:, None] - picked[None]) ** 2).sum(axis=2).min(axis=1)).max()
    assert QUERIES["covering_over_emb"](spark, small).first().radius == pytest.approx(want, abs=1e-6)
