import math
from itertools import product
from statistics import NormalDist

import numpy as np
import pandas as pd
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from evencube import rng
from evencube.functions import normal, objectives
from evencube.operators import covering, designs, discrepancy, fitted, latin, stats, strata
from evencube.plans import planner


def frame(spark, x):
    return spark.createDataFrame(pd.DataFrame({"point_id": np.arange(len(x)), "x": [list(map(float, r)) for r in x]}), "point_id long, x array<double>")


def test_discrepancy_of_centres_on_the_line(spark):
    for count in (1, 2, 7, 64):
        x = (np.arange(count)[:, None] + 0.5) / count
        assert discrepancy.discrepancy_np(x) == pytest.approx(1 / (12 * count**2))
    points = frame(spark, (np.arange(50)[:, None] + 0.5) / 50)
    assert discrepancy.discrepancy(points, 1).first().discrepancy_sq == pytest.approx(1 / (12 * 2500))
    line = points.select(F.element_at("x", 1).alias("v"))
    assert discrepancy.discrepancy_1d(line, "v").first().discrepancy_sq == pytest.approx(1 / (12 * 2500))


def test_tiles_give_the_closed_form(spark, monkeypatch):
    monkeypatch.setattr(discrepancy, "TILE", 40)
    x = np.random.default_rng(0).random((150, 3))
    row = discrepancy.discrepancy(frame(spark, x), 3).first()
    assert row["count"] == 150 and row.discrepancy_sq == pytest.approx(discrepancy.discrepancy_np(x), rel=1e-9)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 300), st.integers(1, 4), st.integers(0, 30), st.booleans())
def test_divide_and_conquer_agrees(count, n, seed, tied):
    x = np.random.default_rng(seed).random((count, n))
    x = np.round(x, 1) if tied else x
    assert discrepancy.discrepancy_dc_np(x) == pytest.approx(discrepancy.discrepancy_np(x), rel=1e-8, abs=1e-12)


def test_discrepancy_in_sql(spark):
    from evencube.functions import udafs

    udafs.register(spark)
    x = np.random.default_rng(3).random((60, 2))
    frame(spark, x).createOrReplaceTempView("cloud")
    rows = spark.sql("SELECT point_id % 2 AS g, discrepancy(x) AS d FROM cloud GROUP BY point_id % 2").collect()
    assert {r.g: pytest.approx(r.d) for r in rows} == {g: discrepancy.discrepancy_np(x[g::2]) for g in (0, 1)}


def test_gap_is_bounded_by_the_modulus_of_continuity():
    """A Lipschitz function's best sampled value misses its minimum by at most its constant times the covering radius."""
    for seed in range(5):
        lo, hi = strata.bsplit_np(50, 2, mode="keyed", seed=seed)
        x = (lo + hi) / 2
        best = np.random.default_rng(seed).random(2)
        gap = np.sqrt(((x - best) ** 2).sum(axis=1)).min()
        assert gap <= covering.covering_exact_2d(x) + 1e-12


def test_exact_radius_in_higher_dimensions():
    lo, hi = strata.grid_np(2, 4)
    assert covering.covering_exact_nd((lo + hi) / 2) == pytest.approx(2 / 4)
    x = np.random.default_rng(2).random((10, 5))
    exact = covering.covering_exact_nd(x)
    assert covering.lower_np(x, 20_000, 1) <= exact + 1e-9 <= fitted.fitted_upper_np(x, 3, 1) + 1e-6


def test_sampled_boxes_estimate_the_integral(spark):
    x = np.random.default_rng(1).random((40, 2))
    row = discrepancy.discrepancy_boxes(frame(spark, x), 2, 6000, seed=1).first()
    assert row.discrepancy_sq == pytest.approx(discrepancy.discrepancy_np(x), rel=0.15)


def test_expected_discrepancy():
    for n in (2, 3):
        got = [discrepancy.discrepancy_np(designs.srs_np(60, n, 1, r)) for r in range(400)]
        error = np.std(got) / math.sqrt(len(got))
        assert abs(np.mean(got) - discrepancy.expected_sq(60, n)) < 4 * error


@pytest.mark.parametrize("k", range(2, 13))
def test_radius_of_grid_centres(k):
    lo, hi = strata.grid_np(k, 2)
    x = (lo + hi) / 2
    assert covering.covering_exact_2d(x) == pytest.approx(math.sqrt(2) / (2 * k))
    assert covering.upper_np(x, lo, hi) == pytest.approx(math.sqrt(2) / (2 * k))
    assert covering.covering_floor(k * k, 2) == 1 / (2 * k)


def test_radius_in_three_dimensions():
    lo, hi = strata.grid_np(2, 3)
    assert covering.covering_exact_nd((lo + hi) / 2) == pytest.approx(math.sqrt(3) / 4)
    x = np.random.default_rng(0).random((12, 3))
    probes = np.random.default_rng(1).random((40_000, 3))
    probes[:8] = list(product([0, 1], repeat=3))
    least = math.sqrt(covering.min_distance_sq(probes, x).max())
    exact = covering.covering_exact_nd(x)
    assert least <= exact + 1e-9 and exact < least * 1.1


@settings(max_examples=25, deadline=None)
@given(st.integers(2, 60), st.integers(0, 50))
def test_bounds_enclose(count, seed):
    lo, hi = strata.bsplit_np(count, 2, mode="keyed", seed=seed)
    x = lo + (hi - lo) * rng.fast_uniform(seed, np.arange(count)[:, None], np.arange(2)[None, :])
    exact = covering.covering_exact_2d(x)
    assert covering.lower_np(x, 500, seed) <= exact + 1e-9
    assert exact <= covering.upper_np(x, lo, hi) + 1e-9
    assert exact <= fitted.fitted_upper_np(x, 3, seed) + 1e-9


def test_corner_distance_by_brute_force(spark):
    r = np.random.default_rng(4)
    for n in (1, 3, 6, 8):
        lo = r.random(n)
        hi = lo + r.random(n)
        x = lo + (hi - lo) * r.random(n)
        want = max(math.dist(x, c) for c in product(*zip(lo, hi)))
        row = spark.createDataFrame([(x.tolist(), lo.tolist(), hi.tolist())], "x array<double>, lo array<double>, hi array<double>")
        assert covering.covering_upper(row).first().upper == pytest.approx(want)


def test_nearest_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(covering, "BLOCK", 30)
    x, p = np.random.default_rng(1).random((100, 3)), np.random.default_rng(2).random((200, 3))
    places = frame(spark, p).withColumnRenamed("point_id", "probe_id").withColumnRenamed("x", "p")
    got = {r.probe_id: r.distance for r in covering.nearest(places, frame(spark, x)).collect()}
    want = np.sqrt(((p[:, None] - x[None]) ** 2).sum(axis=2).min(axis=1))
    assert np.allclose([got[k] for k in range(200)], want)


def test_line_radius_edges(spark):
    one = spark.createDataFrame([(0.25,)], "v double")
    assert covering.covering_exact_1d(one, "v", 0.0, 1.0).first().radius == pytest.approx(0.75)
    tied = spark.createDataFrame([(0.5,), (0.5,), (None,)], "v double")
    assert covering.covering_exact_1d(tied, "v", 0.0, 1.0).first().radius == pytest.approx(0.5)


def test_separation(spark):
    x = np.random.default_rng(5).random((300, 2))
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(axis=2))
    want = d[np.triu_indices(300, 1)].min()
    assert covering.separation(frame(spark, x), 2).first().separation == pytest.approx(want)
    assert covering.separation(frame(spark, x[:1]), 2).first().separation is None
    assert covering.separation(frame(spark, np.repeat(x[:2], 3, axis=0)), 2).first().separation == 0


@pytest.mark.parametrize("count, n", [(101, 2), (97, 4), (64, 3)])
def test_lattice_separation_by_brute_force(count, n):
    for a in (3, 7, 12):
        x = designs.lattice_np(count, n, a)
        d = np.abs(x[:, None] - x[None])
        d = np.sqrt((np.minimum(d, 1 - d) ** 2).sum(axis=2))
        assert designs.lattice_separation(a, count, n) == pytest.approx(d[np.triu_indices(count, 1)].min())


def test_lattice_of_huge_count_uses_decimals(spark):
    count = (1 << 33) + 17
    row = designs.power_lattice(spark, count, 3, a=123_456_789, shift=False).where(F.col("point_id") == 4_000_000_007).first()
    z = designs.generator_powers(123_456_789, count, 3)
    assert np.allclose(row.x, [(4_000_000_007 * v % count) / count for v in z])


def test_radical_inverse_twin(spark):
    got = np.stack(designs.radinv(spark, 60, 5, seed=2).orderBy("point_id").toPandas()["x"])
    assert np.allclose(got, designs.radinv_np(60, 5, 2))
    assert len({tuple(designs.digit_orders(3, s, True)) for s in range(40)}) == 2  # two orders in all for two axes


def test_designs_are_latin(spark):
    for points, count, n in ((designs.lhs(spark, 77, 3, seed=1), 77, 3), (designs.grid_latin(spark, 4, 3, seed=1), 64, 3), (designs.padded_grid(spark, 81, [2, 4, 1], latin=True, seed=2), 81, 7)):
        assert latin.latin_violations(points, count, n).where("empty_bins > 0").count() == 0
    cells = designs.grid_latin(spark, 4, 3, seed=1).select(F.transform("x", lambda v: F.floor(v * 4)).alias("c")).distinct().count()
    assert cells == 64
    for method in (designs.lhs_np(50, 4, 1), designs.padded_grid_np(81, [2, 4], True, 3)):
        assert all(len(np.unique(np.floor(method[:, d] * len(method)))) == len(method) for d in range(method.shape[1]))


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 120), st.integers(1, 4), st.integers(0, 20), st.sampled_from(["random_greedy", "cog", "sweep"]))
def test_matching_is_perfect(count, n, seed, init):
    lo, hi = strata.bsplit_np(count, n, mode="keyed", seed=seed)
    for d in range(n):
        bins = latin.match_axis(lo[:, d], hi[:, d], count, 0, init, seed, d)
        assert sorted(bins.tolist()) == list(range(count))
        low, high = np.maximum(lo[:, d], bins / count), np.minimum(hi[:, d], (bins + 1) / count)
        assert (high - low > 0).all()


def test_matching_components_cover_each_axis(spark):
    made = strata.bsplit_strata(spark, 120, 2)
    got = latin.match_bins(made, 120, "random_greedy", seed=1)
    assert got.where("violation").count() == 0 and got.groupBy("dim").agg(F.count_distinct("bin").alias("n")).where("n <> 120").count() == 0
    parts = latin.components(latin.long_form(made), 120).groupBy("dim").agg(F.count_distinct("comp").alias("n"))
    assert parts.agg(F.max("n").alias("n")).first().n >= 1


def test_centre_order_rarely_misses():
    for count, n, most in ((100, 2, 0), (196, 2, 0), (1000, 2, 4), (500, 2, 20)):
        lo, hi = strata.bsplit_np(count, n, mode="keyed", seed=3)
        x = latin.latin_np(lo, hi, "cog", 1)
        empty = sum(count - len(np.unique(np.floor(x[:, d] * count))) for d in range(n))
        assert empty <= most


def test_global_rank_has_no_single_sort(spark):
    rows = spark.range(5000).select(F.lit(0).alias("g"), "id", F.pmod(F.xxhash64("id"), F.lit(97)).alias("v"))
    got = latin.global_rank(rows, "g", ["v", "id"]).toPandas().sort_values(["v", "id"])
    assert got["rank"].tolist() == list(range(5000))


def test_fitted_partition(spark, monkeypatch):
    x = np.random.default_rng(3).random((400, 3))
    want = fitted.mean_gap_partition(frame(spark, x), 3, tries=2, seed=1).toPandas()
    monkeypatch.setattr(fitted, "LOCAL_POINTS", 60)
    for got in (want, fitted.mean_gap_partition(frame(spark, x), 3, tries=2, seed=1).toPandas()):
        for _, part in got.groupby("try"):
            lo, hi, p = (np.stack(part[c]) for c in ("lo", "hi", "x"))
            assert len(part) == 400 and ((lo <= p) & (p <= hi)).all()
            assert (hi - lo).prod(axis=1).sum() == pytest.approx(1)


def test_fitted_partition_keeps_equal_points_together(spark):
    x = np.array([[0.5, 0.5]] * 5 + [[0.2, 0.5], [0.2, 0.9]])
    got = fitted.mean_gap_partition(frame(spark, x), 2).toPandas()
    assert len(got) == 7 and len({tuple(v) for v in got["lo"].map(tuple) + got["hi"].map(tuple)}) == 3
    assert fitted.covering_upper_fitted(frame(spark, x), 2, tries=2).first().upper > 0
    assert fitted.mean_gap_partition(frame(spark, x[:0]), 2).count() == 0


@pytest.mark.parametrize("rule", fitted.RULES)
def test_subset_picks(spark, rule):
    x = np.random.default_rng(6).random((500, 2)) ** 2
    got = fitted.select_uniform_subset(frame(spark, x), 40, 2, rule)
    assert got.count() == 40 and got.select("point_id").distinct().count() == 40
    with pytest.raises(ValueError):
        fitted.pick_np(x, 3, "other")
    few = frame(spark, np.repeat(x[:3], 4, axis=0))
    assert fitted.select_uniform_subset(few, 10, 2, rule).count() == 3
    assert fitted.select_uniform_subset(few.limit(0), 10, 2, rule).count() == 0


def test_subset_covers_better_than_chance(spark):
    x = np.random.default_rng(7).random((2000, 2)) ** 3
    picked = np.stack(fitted.select_uniform_subset(frame(spark, x), 60, 2).toPandas()["x"])
    chance = x[:60]
    far = lambda p: covering.min_distance_sq(x, p).max()
    assert far(picked) < far(chance)


def test_inverse_normal(spark):
    p = [1e-6, 0.01, 0.02, 0.1, 0.5, 0.77, 0.99, 1 - 1e-6]
    want = [NormalDist().inv_cdf(v) for v in p]
    assert np.allclose(normal.norm_ppf_np(np.array(p)), want, rtol=3e-9, atol=1e-9)
    got = [r.z for r in spark.createDataFrame([(k, v) for k, v in enumerate(p)], "k int, p double").select("k", normal.norm_ppf(F.col("p")).alias("z")).orderBy("k").collect()]
    assert np.allclose(got, want, rtol=3e-9, atol=1e-9)


def test_objective_twins(spark):
    x = np.random.default_rng(8).random((20, 6))
    df = frame(spark, x)
    for name in ("sphere", "rosenbrock", "double_sum", "plate"):
        got = [r.f for r in df.select("point_id", getattr(objectives, name)(F.col("x")).alias("f")).orderBy("point_id").collect()]
        assert np.allclose(got, getattr(objectives, f"{name}_np")(x))


def test_optima_are_zero():
    for name in ("sphere", "rosenbrock", "double_sum", "trigonometric"):
        f = objectives.shifted(name, 4, 1, 2)
        place = f.optimum if name == "trigonometric" else math.pi * (2 * rng.fast_uniform(1, 2, 54, np.arange(4)) - 1)
        assert f(place[None, :])[0] == pytest.approx(0, abs=1e-9)
        assert (f(np.random.default_rng(0).random((50, 4))) >= 0).all()


def test_bootstrap_weights(spark):
    w = spark.range(20_000).select(stats.poisson_weight(rng.uniform(1, "w", F.col("id"))).alias("w")).agg(F.avg("w").alias("m"), F.variance("w").alias("v")).first()
    assert w.m == pytest.approx(1, abs=0.03) and w.v == pytest.approx(1, abs=0.06)


def test_median_ranks_cover():
    low, high = stats.median_ranks(100)
    assert (low, high) == (40, 61)


def test_planner():
    assert planner.integer_root(125, 3) == 5 and planner.integer_root(124, 3) == 4 and planner.integer_root(10**12, 3) == 10_000
    assert planner.discrepancy_method(10**9, 3) == "boxes" and planner.covering_method(100, 5) == "bounds" and planner.covering_method(100, 3) == "exact" and planner.strata_engine(10**9) == "subtree"
