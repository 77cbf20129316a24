"""Data source, SQL functions, files and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evencube.functions import tables as tf
from evencube.operators import strata
from evencube.sources import design_source, tables, udtf
from evencube.streaming import fill


def test_source_prunes_subtrees(spark):
    reader = design_source.CubeDesignReader({"count": "256", "dims": "2", "parts": "16"})
    assert len(reader.partitions()) == 16

    class Bound:
        pass

    from pyspark.sql.datasource import GreaterThan, LessThan

    assert len(list(reader.pushFilters([GreaterThan(("hi1",), 0.8), LessThan(("lo2",), 0.1)]))) == 2
    assert 0 < len(reader.partitions()) < 8


def test_source_reads_all_and_some(spark):
    design_source.register(spark)
    made = spark.read.format("cube_design").option("count", "100").option("dims", "3").load()
    lo, hi = strata.bsplit_np(100, 3)
    assert made.count() == 100
    want = int(((hi[:, 0] > 0.9) & (lo[:, 2] < 0.05)).sum())
    assert made.where("hi1 > 0.9 AND lo3 < 0.05").count() == want
    assert made.where("hi1 > 2").count() == 0


def test_sql_functions(spark):
    udtf.register(spark)
    assert spark.sql("SELECT count(*) AS n FROM bsplit(50, 3)").first().n == 50
    got = spark.sql("SELECT corner_distance(array(0.25D, 0.5D), array(0D, 0D), array(1D, 1D)) AS d").first().d
    assert got == pytest.approx(np.hypot(0.75, 0.5))


@pytest.mark.parametrize("form", ["parquet", "json", "orc", "csv"])
def test_designs_in_files(spark, tmp_path, form):
    flat = strata.bsplit_strata(spark, 20, 2).select("stratum_id", F.element_at("lo", 1).alias("lo1"), (F.col("stratum_id") % 2).alias("rep"))
    tables.write_design(flat, str(tmp_path / form), by=["rep"], form=form)
    back = tables.read_design(spark, str(tmp_path / form), form, "stratum_id long, lo1 double, rep int")
    assert sorted(r.stratum_id for r in back.collect()) == list(range(20)) and back.where("rep = 1").count() == 10


def stream(spark, small):
    schema = spark.read.parquet(f"{small}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(small)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def placed(rows, spark, small):
    batch = spark.read.parquet(f"{small}/events.parquet")
    axes = {"ts": tf.timestamp_axis(F.col("ts")), "value": F.col("value")}
    bounds = tf.ranges(batch, axes)
    return fill.with_stratum(rows, [tf.unit(c, *bounds[k]) for k, c in axes.items()], 64)


def finished(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return df.sparkSession.sql(f"SELECT * FROM {name}")


def test_windows_fill_as_in_batch(spark, small):
    rows = placed(stream(spark, small), spark, small)
    got = finished(fill.tumbling_fill(rows, "ts", "1 day", late="1 hour"), "tumbling", "complete")
    batch = placed(spark.read.parquet(f"{small}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")), spark, small)
    want = fill.tumbling_fill(batch, "ts", "1 day")
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0 and got.count() > 10


def test_first_of_each_stratum(spark, small):
    rows = placed(stream(spark, small), spark, small)
    got = finished(fill.first_per_stratum(rows, "ts", "1 day", "2 days").select("start", "stratum_id", "event_id"), "firsts", "append")
    assert got.count() == got.select("start", "stratum_id").distinct().count() > 0


def test_state_counts_every_event(spark, small):
    rows = placed(stream(spark, small), spark, small)
    got = finished(fill.newest_per_stratum(rows, "ts", "value", late="40 days", keep="60 days"), "newest", "update")
    assert got.groupBy("stratum_id").agg(F.max("seen").alias("n")).agg(F.sum("n").alias("n")).first().n == spark.read.parquet(f"{small}/events.parquet").count()


def test_reservoirs_do_not_depend_on_arrival(spark, small):
    from evencube import rng

    rows = placed(stream(spark, small), spark, small)
    got = finished(fill.reservoir_per_stratum(rows, "ts", "event_id", 5, late="40 days", keep="60 days", seed=1), "reservoir", "update")
    batch = placed(spark.read.parquet(f"{small}/events.parquet"), spark, small).select("stratum_id", "event_id").collect()
    want: dict = {}
    for r in batch:
        want.setdefault(r.stratum_id, []).append((rng.uniform_py(1, "reservoir", r.event_id), r.event_id))
    last = {r.stratum_id: r["keys"] for r in got.collect()}
    assert last == {s: sorted(i for _, i in sorted(v)[:5]) for s, v in want.items()}


def test_epochs_are_written_once(spark, small, tmp_path):
    rows = placed(stream(spark, small), spark, small).select("event_id", "stratum_id")
    for _ in range(2):  # a restart finds its checkpoint and adds nothing
        q = fill.write_epochs(rows, str(tmp_path / "out"), str(tmp_path / "state"))
        try:
            q.processAllAvailable()
        finally:
            q.stop()
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == back.select("event_id").distinct().count() == spark.read.parquet(f"{small}/events.parquet").count()


def test_late_rows_are_told_apart(spark, small):
    events = spark.read.parquet(f"{small}/events.parquet")
    got = fill.split_late(events, "ts", "5 days")
    newest = events.agg(F.max("ts").alias("t")).first().t
    import datetime

    assert got.where("late").count() == events.where(F.col("ts") < F.lit(newest - datetime.timedelta(days=5))).count() > 0


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, small):
    """Filters and columns reach the scan; designs, draws and assignment neither shuffle nor leave the JVM."""
    from evencube.operators import designs, draws
    from evencube.workloads import table_queries

    boxed = plan(table_queries.rows_in_box(spark, small))
    assert "PushedFilters: [IsNotNull(l_quantity)" in boxed and "l_tax" not in boxed
    assert "BatchEvalPython" not in boxed and "ArrowEvalPython" not in boxed
    for df in (designs.lhs(spark, 1000, 3), designs.radinv(spark, 1000, 3), designs.padded_grid(spark, 625, [2, 1], latin=True), designs.power_lattice(spark, 101, 3, a=7), draws.draw(strata.bsplit_strata(spark, 100, 2), 2)):
        text = plan(df)
        assert "Exchange" not in text and "Python" not in text and "Join" not in text
    assert plan(strata.bsplit_strata(spark, 10**6, 3)).count("Exchange") <= 1  # roots only


def test_scaling_edges(spark):
    rows = spark.createDataFrame([(1, 5.0, 1), (2, 5.0, None), (3, 5.0, 3)], "id long, a double, b int")
    got = {r.point_id: r.x for r in tf.scaled_points(rows, F.col("id"), {"a": F.col("a"), "b": F.col("b")}).collect()}
    assert got == {1: [0.0, 0.0], 2: None, 3: [0.0, 1.0]}
    assert tf.ranges(rows.limit(0), {"a": F.col("a")}) == {"a": (0.0, 1.0)}
