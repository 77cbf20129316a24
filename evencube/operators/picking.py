"""Strata laid over table rows: assignment, counting, picking and stratified means."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng
from ..plans import planner
from . import strata
from .covering import distance_sq


def assign_by_descent(points: DataFrame, count: int, n: int, x: str = "x", **how) -> DataFrame:
    """``points`` with stratum_id, by descending the split tree: no join, no exchange. Null points get null."""
    return points.withColumn("stratum_id", strata.stratum_of(F.col(x), count, n, **how))


def assign_by_range_join(points: DataFrame, boxes: DataFrame, n: int, x: str = "x") -> DataFrame:
    """``points`` with stratum_id by a range join against broadcast boxes, for strata that follow no tree.

    Boxes are half open; those at the region's upper edge also hold their edge.
    More boxes than may be broadcast raise ValueError.
    """
    if boxes.count() > planner.BROADCAST_STRATA:
        raise ValueError("too many strata to broadcast; assign by descent")
    top = boxes.agg(*[F.max(F.element_at("hi", d)).alias(f"t{d}") for d in range(1, n + 1)]).first()
    inside = F.lit(True)
    for d in range(1, n + 1):
        v, lo, hi = F.element_at(x, d), F.element_at("lo", d), F.element_at("hi", d)
        inside = inside & (v >= lo) & ((v < hi) | ((v == hi) & (hi == F.lit(top[f"t{d}"]))))
    return points.join(F.broadcast(boxes.select("stratum_id", "lo", "hi")), inside).drop("lo", "hi")


def fill_counts(assigned: DataFrame) -> DataFrame:
    return assigned.where("stratum_id is not null").groupBy("stratum_id").agg(F.count("*").alias("rows"))


def empty_strata(boxes: DataFrame, assigned: DataFrame) -> DataFrame:
    return boxes.join(fill_counts(assigned), "stratum_id", "left_anti")


def filled_strata(boxes: DataFrame, assigned: DataFrame) -> DataFrame:
    return boxes.join(fill_counts(assigned), "stratum_id", "left_semi")


def nearest_to_centre(assigned: DataFrame, count: int, n: int, point_id: str = "point_id", x: str = "x", **how) -> DataFrame:
    """(stratum_id, point_id, distance): of every filled stratum the row nearest to its centre, ties to the smallest id; partial minima, no sort."""
    rows = assigned.where("stratum_id is not null")
    if count <= planner.BROADCAST_STRATA:
        boxes = strata.bsplit_strata(rows.sparkSession, count, n, **how).select("stratum_id", F.struct("lo", "hi").alias("box_"))
        boxed = rows.join(F.broadcast(boxes), "stratum_id")
    else:
        boxed = rows.withColumn("box_", strata.leaf_box(F.col("stratum_id"), count, n, **how))
    centre = F.zip_with("box_.lo", "box_.hi", lambda low, h: (low + h) / 2)
    d = F.sqrt(distance_sq(F.col(x), centre))
    best = boxed.groupBy("stratum_id").agg(F.min(F.struct(F.round(d, 12).alias("distance"), F.col(point_id).alias("point_id"))).alias("m"))
    return best.select("stratum_id", "m.point_id", "m.distance")


def nearest_to_centres(points: DataFrame, n: int, boxes: dict[int, tuple[np.ndarray, np.ndarray]], point_id: str = "point_id", x: str = "x") -> DataFrame:
    """(count, stratum_id, point_id, x): the row nearest to the centre of every filled stratum of several small designs of the unit cube, ties to the smallest id.

    ``boxes`` has (lo, hi) of each design by its count. One pass over the rows for
    all designs: a task sends one row a stratum. Null points take no part.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[tuple[int, int], tuple] = {}
        for batch in batches:
            ids, p = batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
            for count, (lo, hi) in boxes.items():
                for k in range(count):
                    # half open, but the cube's upper edge belongs to its last boxes
                    inside = np.ones(len(p), bool)
                    for d in range(n):
                        v = p[:, d]
                        inside &= (v >= lo[k, d]) & ((v <= 1) if hi[k, d] == 1 else (v < hi[k, d]))
                    at = np.flatnonzero(inside)
                    if not len(at):
                        continue
                    far = np.zeros(len(at))
                    for d in range(n):
                        far += (p[at, d] - (lo[k, d] + hi[k, d]) / 2) ** 2
                    at = at[far == far.min()]
                    one = at[ids[at].argmin()]
                    found = (float(far.min()), int(ids[one]), p[one].tolist())
                    best[count, k] = min(best.get((count, k), found), found)
        if best:
            rows = [(c, k, *b) for (c, k), b in best.items()]
            yield pa.RecordBatch.from_arrays([pa.array(v) for v in zip(*rows)], names=["count", "stratum_id", "far", "id", "x"])

    known = points.where(F.col(x).isNotNull()).select(F.col(point_id).cast("long").alias("id"), F.slice(x, 1, n).alias("x"))
    found = known.mapInArrow(run, "count long, stratum_id long, far double, id long, x array<double>")
    best = found.groupBy("count", "stratum_id").agg(F.min(F.struct("far", "id", "x")).alias("m"))
    return best.select("count", "stratum_id", F.col("m.id").alias("point_id"), "m.x")


def pick_k(assigned: DataFrame, k: int, point_id: str = "point_id", seed: int = 0) -> DataFrame:
    """(stratum_id, point_id): k keyed rows of every stratum; only the k smallest keys of each task travel."""
    ranked = assigned.where("stratum_id is not null").withColumn("u_", rng.uniform(seed, "pick", F.col(point_id)))
    w = Window.partitionBy("stratum_id").orderBy("u_", point_id)
    return ranked.withColumn("k_", F.row_number().over(w)).where(F.col("k_") <= k).select("stratum_id", F.col(point_id).alias("point_id"))


def stratified_mean(assigned: DataFrame, value: Column, k: int, point_id: str = "point_id", seed: int = 0) -> DataFrame:
    """Mean estimated from k keyed rows a stratum, weighted by the strata's sizes, beside the mean of all rows; one row."""
    rows = assigned.where("stratum_id is not null").withColumn("v_", value.cast("double")).where("v_ is not null")
    w = Window.partitionBy("stratum_id").orderBy(rng.uniform(seed, "pick", F.col(point_id)), point_id)
    picked = rows.withColumn("k_", F.row_number().over(w)).where(F.col("k_") <= k).groupBy("stratum_id").agg(F.avg("v_").alias("m"))
    sizes = rows.groupBy("stratum_id").agg(F.count("*").alias("size"), F.sum("v_").alias("total"))
    return picked.join(sizes, "stratum_id").agg((F.sum(F.col("m") * F.col("size")) / F.sum("size")).alias("stratified"), (F.sum("total") / F.sum("size")).alias("all_rows"), F.sum("size").alias("rows"))


def ntile_strata(rows: DataFrame, by: str, value: str, key: str, parts: int) -> DataFrame:
    """``rows`` with stratum_id: ``parts`` equal-count strata of a value inside every group; groups may hold any share, so ranks come from range counts."""
    from .latin import global_rank

    ranked = global_rank(rows.where(F.col(value).isNotNull()), by, [value, key])
    sizes = rows.where(F.col(value).isNotNull()).groupBy(by).agg(F.count("*").alias("n_"))
    return ranked.join(F.broadcast(sizes), by).withColumn("stratum_id", F.floor(F.col("rank") * parts / F.col("n_")).cast("long")).drop("rank", "n_")
