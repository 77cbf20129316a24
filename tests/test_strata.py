import numpy as np
import pandas as pd
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from evencube import rng
from evencube.operators import draws, picking, strata
from evencube.plans import counts, planner


def test_shares():
    assert [counts.smaller_share(c) for c in (2, 3, 5, 6, 10, 12)] == [1, 1, 2, 2, 4, 6]
    assert [counts.smaller_share(c, False) for c in (6, 10)] == [3, 5]


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 600), st.integers(1, 10), st.booleans(), st.sampled_from(["fixed", "keyed"]), st.integers(0, 99))
def test_invariants(count, n, rule, mode, seed):
    lo, hi = strata.bsplit_np(count, n, rule, mode, seed)
    sides = hi - lo
    assert len(lo) == count
    assert np.allclose(sides.prod(axis=1), 1 / count)
    assert (sides.min(axis=1) / sides.max(axis=1)).min() >= 1 / 3 - 1e-9
    # disjoint: every centre lies in its own box only
    centre = (lo + hi) / 2
    for c in centre[:20]:
        assert ((lo <= c) & (c < hi)).all(axis=1).sum() == 1


@pytest.mark.parametrize("rule, ratio", [(True, 1 / 1.7777777777777777), (False, 1 / 2.7777777777777777)])
def test_side_ratio_of_144(rule, ratio):
    for mode, seed in (("fixed", 0), ("keyed", 1), ("keyed", 2)):
        lo, hi = strata.bsplit_np(144, 2, rule, mode, seed)
        assert np.isclose(((hi - lo).min(axis=1) / (hi - lo).max(axis=1)).min(), ratio)


@pytest.mark.parametrize("count, n", [(4, 2), (16, 2), (64, 2), (256, 2), (8, 3), (64, 3), (512, 3)])
def test_powers_give_the_grid(count, n):
    ours = {tuple(np.round(np.r_[a, b], 12)) for a, b in zip(*strata.bsplit_np(count, n))}
    grid = {tuple(np.round(np.r_[a, b], 12)) for a, b in zip(*strata.grid_np(planner.integer_root(count, n), n))}
    assert ours == grid


@pytest.mark.parametrize("mode", ["fixed", "keyed"])
def test_engines_agree(spark, mode):
    frames = {e: strata.bsplit_strata(spark, 97, 3, mode=mode, seed=3, engine=e).orderBy("stratum_id").toPandas() for e in ("descent", "levels")}
    for c in ("lo", "hi"):
        assert np.allclose(np.stack(frames["descent"][c]), np.stack(frames["levels"][c]))
    sub = strata.bsplit_strata(spark, 97, 3, mode=mode, seed=3, engine="subtree").orderBy("stratum_id").toPandas()
    lo, hi = strata.bsplit_np(97, 3, mode=mode, seed=3)
    assert np.allclose(np.stack(sub["lo"]), lo) and np.allclose(np.stack(sub["hi"]), hi)
    if mode == "fixed":
        assert np.allclose(np.stack(frames["descent"]["lo"]), lo)


def test_large_subtrees_are_opened_in_chunks(monkeypatch):
    monkeypatch.setattr(strata, "CHUNK", 50)
    batches = list(strata._leaves(0, 333, [0.0, 0.0], [1.0, 1.0], True, "fixed", 0))
    assert len(batches) > 5 and sum(b.num_rows for b in batches) == 333
    assert [i for b in batches for i in b["stratum_id"].to_pylist()] == list(range(333))


def test_any_box_and_bad_input(spark):
    lo, hi = strata.bsplit_np(10, 2, lo=[-1, 5], hi=[3, 5.5])
    assert np.allclose((hi - lo).prod(axis=1), 0.2) and lo[:, 0].min() == -1 and hi[:, 1].max() == 5.5
    for bad in ({"count": 0, "n": 2}, {"count": 3, "n": 0}, {"count": 3, "n": 2, "lo": [0, 1], "hi": [1, 0]}, {"count": 3, "n": 1, "mode": "other"}):
        with pytest.raises(ValueError):
            strata.bsplit_strata(spark, **bad)


@pytest.mark.parametrize("count, mode", [(1, "fixed"), (37, "fixed"), (37, "keyed"), (700, "keyed"), (700, "fixed")])
def test_descent_finds_the_box(spark, count, mode):
    pts = np.random.default_rng(1).random((300, 2))
    pts[:4] = [[0, 0], [1, 1], [0, 1], [0.5, 0.5]]
    points = spark.createDataFrame(pd.DataFrame({"point_id": range(300), "x": pts.tolist()}))
    boxes = {r.stratum_id: (r.lo, r.hi) for r in strata.bsplit_strata(spark, count, 2, mode=mode, seed=9, engine="descent").collect()}
    for r in picking.assign_by_descent(points, count, 2, mode=mode, seed=9).collect():
        lo, hi = boxes[r.stratum_id]
        assert all(a <= v and (v < b or b == 1) for v, a, b in zip(r.x, lo, hi))


def test_vectorised_descent_agrees(spark, monkeypatch):
    pts = np.random.default_rng(2).random((500, 3))
    points = spark.createDataFrame(pd.DataFrame({"point_id": range(500), "x": pts.tolist()})).repartition(3)
    want = {r.point_id: r.stratum_id for r in picking.assign_by_descent(points, 300, 3).collect()}
    monkeypatch.setattr(strata, "TREE_LEAVES", 10)
    got = {r.point_id: r.stratum_id for r in picking.assign_by_descent(points, 300, 3).collect()}
    assert want == got


def test_null_points_have_no_stratum(spark, monkeypatch):
    rows = spark.createDataFrame([(1, [0.2, 0.3]), (2, None), (3, [0.1, None]), (4, [float("nan"), 0.5])], "point_id long, x array<double>")
    for limit in (256, 2, 1):
        monkeypatch.setattr(strata, "CASE_LEAVES", limit if limit > 2 else 1)
        monkeypatch.setattr(strata, "TREE_LEAVES", 20_000 if limit > 1 else 1)
        got = {r.point_id: r.stratum_id for r in picking.assign_by_descent(rows, 9, 2).collect()}
        assert got[1] is not None and got[2] is None and got[3] is None and got[4] is None


def test_range_join_equals_descent(spark):
    pts = np.random.default_rng(3).random((400, 2))
    points = spark.createDataFrame(pd.DataFrame({"point_id": range(400), "x": pts.tolist()}))
    a = picking.fill_counts(picking.assign_by_descent(points, 50, 2))
    b = picking.fill_counts(picking.assign_by_range_join(points, strata.bsplit_strata(spark, 50, 2), 2))
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0
    plan = picking.assign_by_descent(points, 50, 2)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Exchange" not in plan


def test_draws_stay_inside_and_narrow_with_b(spark):
    made = strata.bsplit_strata(spark, 200, 2)
    spread = {}
    for b in (1, 4, 16, None):
        pdf = draws.draw(made, b, seed=1).toPandas()
        x, lo, hi = (np.stack(pdf[c]) for c in ("x", "lo", "hi"))
        assert ((lo <= x) & (x <= hi)).all()
        spread[b] = float((((x - lo) / (hi - lo) - 0.5) ** 2).mean())
    assert spread[1] > spread[4] > spread[16] > 1e-4 and spread[None] < 1e-20
    assert np.isclose(spread[1], 1 / 12, rtol=0.2) and np.isclose(spread[4], 1 / 48, rtol=0.3)


def test_augment_adds_k_per_stratum(spark):
    made = strata.bsplit_strata(spark, 30, 2)
    more = draws.augment(made, 3, seed=4)
    assert more.count() == 90 and more.groupBy("stratum_id").count().where("count <> 3").count() == 0
    assert more.select("x").distinct().count() == 90


@pytest.mark.parametrize("n", [1, 2, 7, 100, 625, 1000])
def test_permutation_is_a_bijection(spark, n):
    want = rng.permute_np(np.arange(n), n, 5, 2) if n > 1 else np.zeros(1)
    got = [r.v for r in spark.range(n).select(rng.permute(F.col("id"), n, 5, 2).alias("v"), "id").orderBy("id").collect()]
    assert sorted(got) == list(range(n)) and got == want.tolist()


def test_uniform_twins(spark):
    got = [r.u for r in spark.range(5).select("id", rng.uniform(3, "t", F.col("id"), 7).alias("u")).orderBy("id").collect()]
    assert got == [rng.uniform_py(3, "t", k, 7) for k in range(5)]


def test_auto_strata_uses_the_grid(spark):
    assert strata.auto_strata(spark, 49, 2).select("lo").distinct().count() == 49
    assert strata.side_ratio(strata.auto_strata(spark, 49, 2)).first().side_ratio == pytest.approx(1)
    assert strata.auto_strata(spark, 50, 2).count() == 50


def test_picking_edges(spark):
    empty = spark.createDataFrame([], "point_id long, x array<double>")
    placed = picking.assign_by_descent(empty, 9, 2)
    assert picking.fill_counts(placed).count() == 0
    assert picking.nearest_to_centre(placed, 9, 2).count() == 0
    assert picking.empty_strata(strata.bsplit_strata(spark, 9, 2), placed).count() == 9
    same = spark.createDataFrame([(k, [0.5, 0.5]) for k in range(20)], "point_id long, x array<double>")
    placed = picking.assign_by_descent(same, 9, 2)
    assert picking.fill_counts(placed).first().rows == 20
    assert picking.nearest_to_centre(placed, 9, 2).first().point_id == 0
    assert picking.pick_k(placed, 50).count() == 20


def test_stratified_mean_beats_plain_rows_on_a_trend(spark):
    rng_ = np.random.default_rng(0)
    x = rng_.random((4000, 1))
    points = spark.createDataFrame(pd.DataFrame({"point_id": range(4000), "x": x.tolist(), "y": x[:, 0] * 10}))
    row = picking.stratified_mean(picking.assign_by_descent(points, 40, 1), F.col("y"), 2, seed=1).first()
    assert abs(row.stratified - row.all_rows) < 0.15 and row.rows == 4000
