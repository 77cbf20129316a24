"""Queries that once made all their data up follow the given rows."""

import numpy as np
import pytest
from conftest import rows_of

from evencube.operators import covering, picking, strata
from evencube.workloads import measure_queries, registry, strata_queries  # noqa: F401


def test_strata_hold_the_rows_of_the_table(spark, small):
    rows = spark.read.parquet(f"{small}/lineitem.parquet").count()
    for name in ("bsplit_144_on", "bsplit_144_off", "bsplit_keyed_100", "bsplit_levels_100"):
        assert registry.QUERIES[name](spark, small).agg({"rows": "sum"}).first()[0] == rows


@pytest.mark.parametrize("count", [400, 7, 0])
def test_tightness_is_that_of_the_orders(spark, duck, tmp_path, count):
    chosen = f"SELECT * FROM orders ORDER BY md5(o_orderkey::VARCHAR) LIMIT {count}"
    duck.execute(f"COPY ({chosen}) TO '{tmp_path}/orders.parquet' (FORMAT parquet)")
    found = registry.QUERIES["bound_tightness"](spark, str(tmp_path))
    got = rows_of(found.columns, found.collect())
    here = duck.cursor()
    here.execute(f"CREATE TEMP VIEW orders AS SELECT * FROM '{tmp_path}/orders.parquet'")
    want = here.execute(registry.ORACLE_SQL["bound_tightness"])
    assert got == rows_of([d[0] for d in want.description], want.fetchall())
    # for the strata's own centres, bound and radius are equal at these sizes
    assert len(got) == 2 * (count > 0) and all(ratio > 1 for ratio in found.toPandas()["mean_ratio"])


def test_rows_nearest_to_centres(spark):
    boxes = {c: strata.tree_boxes_np(c, 2, mode="keyed", seed=5) for c in (1, 9)}
    for c, (lo, hi) in boxes.items():
        held = strata.bsplit_strata(spark, c, 2, mode="keyed", seed=5).orderBy("stratum_id").collect()
        assert np.array_equal(lo, [r["lo"] for r in held]) and np.array_equal(hi, [r["hi"] for r in held])
    x = np.r_[np.random.default_rng(1).random((300, 2)), [[1.0, 1.0], [0.0, 1.0]]]
    x = np.r_[x, x]
    rows = spark.createDataFrame([(len(x) - k, [float(a) for a in p]) for k, p in enumerate(x)] + [(-1, None)], "point_id long, x array<double>")
    picked = picking.nearest_to_centres(rows.repartition(5), 2, boxes).collect()
    assert len(picked) == 10
    for r in picked:
        lo, hi = (side[r.stratum_id] for side in boxes[r["count"]])
        inside = ((x >= lo) & ((x < hi) | ((x == hi) & (hi == 1)))).all(axis=1)
        far = np.where(inside, ((x - (lo + hi) / 2) ** 2).sum(axis=1), np.inf)
        assert r.x == x[far.argmin()].tolist() and r.point_id == min(len(x) - np.flatnonzero(far == far.min()))


def test_boxes_without_a_row_are_reached_from_others():
    lo, hi = strata.tree_boxes_np(4, 2)
    x = np.array([[0.2, 0.3]])
    box = np.flatnonzero(((x >= lo) & (x < hi)).all(axis=1))
    assert covering.upper_in_boxes_np(x, box, lo, hi) == pytest.approx(np.hypot(0.8, 0.7)) == covering.covering_exact_nd(x)
