"""Every registered query of the engine against its SQL on the small tables."""

import pytest

from evencube.workloads import measure_queries, registry, strata_queries, table_queries  # noqa: F401


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_query_agrees_with_sql(name, agrees):
    agrees(registry.QUERIES[name], registry.ORACLE_SQL[name])


def test_radius_bounds_enclose_the_exact_radius(spark):
    from evencube.workloads.experiments import radius_bounds

    rows = radius_bounds(spark, (2, 3), (4, 7, 16, 25)).toPandas()
    assert (rows["lower"] <= rows["exact"] + 1e-9).all() and (rows["exact"] <= rows["upper"] + 1e-9).all()
    assert (rows["normalized"] >= 1 - 1e-9).all()


def test_fitted_bounds(spark, small):
    row = registry.QUERIES["fitted_upper_bounds"](spark, small).first()
    assert 0 < row.lower <= row.upper


def test_bound_tightness(spark, small):
    rows = registry.QUERIES["bound_tightness"](spark, small).toPandas()
    assert ((rows["mean_ratio"] >= 1 - 1e-9) & (rows["mean_ratio"] < 1.2)).all() and rows["tight"].between(0, 1).all()


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 144
    assert set(entry.oracle_sql()) <= set(entry.queries())
