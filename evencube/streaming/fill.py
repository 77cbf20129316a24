"""Streams of points laid over strata: how windows fill them.

Every event finds its stratum by descent, without state. Windows keep one row
per stratum at most, so state is bounded by strata times open windows and goes
when the watermark passes.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from .. import rng
from ..operators.strata import stratum_of


def with_stratum(events: DataFrame, axes: list[Column], count: int) -> DataFrame:
    """``events`` with stratum_id; rows with a null coordinate get null."""
    return events.withColumn("stratum_id", stratum_of(F.array(*axes), count, len(axes)))


def tumbling_fill(placed: DataFrame, time: str, width: str, late: str | None = None) -> DataFrame:
    """(start, strata, events) per tumbling window: filled strata and events; with ``late`` under a watermark."""
    rows = placed.withWatermark(time, late) if late else placed
    found = rows.where("stratum_id is not null").groupBy(F.window(time, width)).agg(F.size(F.collect_set("stratum_id")).cast("long").alias("strata"), F.count("*").alias("events"))
    return found.select(F.col("window.start").alias("start"), "strata", "events")


def sliding_fill(placed: DataFrame, time: str, width: str, step: str, late: str | None = None) -> DataFrame:
    rows = placed.withWatermark(time, late) if late else placed
    found = rows.where("stratum_id is not null").groupBy(F.window(time, width, step)).agg(F.size(F.collect_set("stratum_id")).cast("long").alias("strata"), F.count("*").alias("events"))
    return found.select(F.col("window.start").alias("start"), "strata", "events")


def session_fill(placed: DataFrame, time: str, gap: str, key: str, late: str | None = None) -> DataFrame:
    """(key, start, end, strata, events) per session of a key."""
    rows = placed.withWatermark(time, late) if late else placed
    found = rows.where("stratum_id is not null").groupBy(key, F.session_window(time, gap)).agg(F.size(F.collect_set("stratum_id")).cast("long").alias("strata"), F.count("*").alias("events"))
    return found.select(key, F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "strata", "events")


def first_per_stratum(placed: DataFrame, time: str, width: str, late: str) -> DataFrame:
    """The first event seen of each stratum in each window: a streaming stratified sample."""
    rows = placed.withWatermark(time, late).where("stratum_id is not null").withColumn("start", F.window(time, width).start)
    return rows.dropDuplicatesWithinWatermark(["start", "stratum_id"])


def newest_per_stratum(placed: DataFrame, time: str, value: str, late: str = "1 hour", keep: str = "2 hours") -> DataFrame:
    """(stratum_id, seen, value): running count and latest value per stratum, forgotten ``keep`` after its last event."""
    state = "seen long, at timestamp, value double"
    horizon = pd.Timedelta(keep)

    def step(key: tuple, batches: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        if held.hasTimedOut:
            held.remove()
            return
        seen, at, last = held.get if held.exists else (0, pd.Timestamp(0), 0.0)
        for pdf in batches:
            seen += len(pdf)
            newest = pdf.loc[pdf[time].idxmax()]
            if newest[time] >= at:
                at, last = newest[time], float(newest[value])
        held.update((seen, at, last))
        held.setTimeoutTimestamp(max(int((at + horizon).timestamp() * 1000), held.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"stratum_id": [key[0]], "seen": [seen], "value": [last]})

    rows = placed.withWatermark(time, late).where("stratum_id is not null").select("stratum_id", time, value)
    return rows.groupBy("stratum_id").applyInPandasWithState(step, "stratum_id long, seen long, value double", state, "update", GroupStateTimeout.EventTimeTimeout)


def reservoir_per_stratum(placed: DataFrame, time: str, key: str, k: int, late: str = "1 hour", keep: str = "2 hours", seed: int = 0) -> DataFrame:
    """(stratum_id, keys): a uniform sample of k event keys per stratum, kept while its events come.

    Every event has a keyed number; a stratum holds the k smallest it has met,
    so the sample does not depend on the order of arrival and state is bounded
    by k rows a stratum.
    """
    state = "numbers array<double>, ids array<long>, at timestamp"
    horizon = pd.Timedelta(keep)

    def step(group: tuple, batches: Iterator[pd.DataFrame], held: GroupState) -> Iterator[pd.DataFrame]:
        if held.hasTimedOut:
            held.remove()
            return
        numbers, ids, at = held.get if held.exists else ([], [], pd.Timestamp(0))
        best = dict(zip(ids, numbers))
        for pdf in batches:
            best.update(zip(pdf["id_"].tolist(), pdf["u_"].tolist()))
            at = max(at, pdf[time].max())
        chosen = sorted(best.items(), key=lambda item: (item[1], item[0]))[:k]
        held.update(([u for _, u in chosen], [i for i, _ in chosen], at))
        held.setTimeoutTimestamp(max(int((at + horizon).timestamp() * 1000), held.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"stratum_id": [group[0]], "keys": [sorted(i for i, _ in chosen)]})

    rows = placed.withWatermark(time, late).where("stratum_id is not null")
    rows = rows.select("stratum_id", time, F.col(key).cast("long").alias("id_"), rng.uniform(seed, "reservoir", F.col(key)).alias("u_"))
    return rows.groupBy("stratum_id").applyInPandasWithState(step, "stratum_id long, keys array<long>", state, "update", GroupStateTimeout.EventTimeTimeout)


def write_epochs(df: DataFrame, path: str, checkpoint: str):
    """Starts a stream into ``path``/epoch=N: a repeated micro-batch overwrites its own folder, so rows arrive exactly once."""

    def put(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return df.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).start()


def split_late(placed: DataFrame, time: str, late: str) -> DataFrame:
    """Batch rows with late: whether a row's time lies further behind the newest row than ``late`` (what a watermark would drop); one broadcast maximum."""
    newest = placed.agg(F.max(time).alias("newest_"))
    return placed.join(F.broadcast(newest)).withColumn("late", F.col(time) < F.col("newest_") - F.expr(f"INTERVAL {late}")).drop("newest_")
