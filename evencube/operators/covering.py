"""Covering radius: exact where feasible, else bounds from below and above.

The covering radius of a point set is the largest distance from anywhere in
the region to its nearest point.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng
from ..plans import planner


def distance_sq(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda acc, v: acc + v)


def corner_distance(x: Column, lo: Column, hi: Column) -> Column:
    """Distance from a point to the farthest corner of its box."""
    reach = F.zip_with(x, F.zip_with(lo, hi, lambda low, h: F.struct(low.alias("lo"), h.alias("hi"))), lambda v, s: F.greatest(v - s.lo, s.hi - v))
    return F.sqrt(F.aggregate(reach, F.lit(0.0), lambda acc, v: acc + v * v))


def covering_upper(points: DataFrame) -> DataFrame:
    """Upper bound from points in boxes that cover the region (x, lo, hi), one row; boxes may overlap."""
    return points.agg(F.max(corner_distance(F.col("x"), F.col("lo"), F.col("hi"))).alias("upper"))


def covering_floor(count: int, n: int) -> float:
    """No point set of this size covers the unit cube with a smaller radius in the maximum norm, so neither in the Euclidean."""
    return 1 / (2 * planner.integer_root(count, n))


def probes(spark: SparkSession, count: int, n: int, seed: int = 0) -> DataFrame:
    """(probe_id, p): keyed uniform places of the unit cube."""
    axes = [rng.uniform(seed, "probe", F.col("id"), d) for d in range(n)]
    return spark.range(count).select(F.col("id").alias("probe_id"), F.array(*axes).alias("p"))


#: Points held by each task when nearest distances are taken in blocks.
BLOCK = 4096

#: Places that one task compares with a block.
PLACES = 65_536


def nearest(space: DataFrame, points: DataFrame, space_id: str = "probe_id", space_x: str = "p", point_x: str = "x") -> DataFrame:
    """(space_id, distance) to the nearest point, by blocks of points against all of space.

    Points are dealt to blocks of about ``BLOCK``, places to slices of about
    ``PLACES``, so that a task's size stays when either grows; every place meets
    each block once and its partial minima are combined. Rows with a null coordinate array
    take no part.
    """
    chosen = points.where(F.col(point_x).isNotNull()).select(F.col(point_x).alias("x"))
    blocks = max(1, -(-chosen.count() // BLOCK))
    right = chosen.withColumn("block", F.pmod(F.monotonically_increasing_id(), F.lit(blocks)).cast("int"))
    slices_ = max(-(-space.count() // PLACES), space.sparkSession.sparkContext.defaultParallelism // blocks, 1)
    piece = F.pmod(F.xxhash64(space_id), F.lit(slices_)).cast("int")
    left = space.where(F.col(space_x).isNotNull()).select(F.col(space_id).alias("id"), F.col(space_x).alias("p"), piece.alias("piece"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"))
    right = right.withColumn("piece", F.explode(F.sequence(F.lit(0), F.lit(slices_ - 1))))
    kind = space.schema[space_id].dataType.simpleString()

    def run(places: pd.DataFrame, pts: pd.DataFrame) -> pd.DataFrame:
        if places.empty or pts.empty:
            return pd.DataFrame({"id": [], "d": []}).astype({"id": "int64", "d": "float64"})
        p, x = np.stack(places["p"].to_numpy()), np.stack(pts["x"].to_numpy())
        best = np.empty(len(p))
        for k in range(0, len(p), 256):
            best[k : k + 256] = min_distance_sq(p[k : k + 256], x)
        return pd.DataFrame({"id": places["id"], "d": best})

    found = left.groupBy("piece", "block").cogroup(right.groupBy("piece", "block")).applyInPandas(run, f"id {kind}, d double")
    return found.groupBy(F.col("id").alias(space_id)).agg(F.sqrt(F.min("d")).alias("distance"))


def min_distance_sq(p: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Squared distance of every p to its nearest x, from differences (no cancellation)."""
    best = np.full(len(p), np.inf)
    for k in range(0, len(x), 1024):
        d = np.zeros((len(p), len(x[k : k + 1024])))
        for axis in range(p.shape[1]):
            d += (p[:, axis, None] - x[None, k : k + 1024, axis]) ** 2
        np.minimum(best, d.min(axis=1), out=best)
    return best


def covering_lower(points: DataFrame, n: int, m: int, seed: int = 0) -> DataFrame:
    """Lower bound from m keyed probes, one row; linear in probes times points."""
    places = probes(points.sparkSession, m, n, seed)
    return nearest(places, points).agg(F.max("distance").alias("lower"))


def covering_over(points: DataFrame, space: DataFrame, space_id: str, space_x: str) -> DataFrame:
    """Covering radius when the region is the finite set ``space``, one row."""
    return nearest(space, points, space_id, space_x).agg(F.max("distance").alias("radius"))


def covering_exact_1d(points: DataFrame, value: str, lo: float, hi: float) -> DataFrame:
    """Exact radius on a line: half gaps between neighbours and whole gaps at the ends, one row.

    Neighbours are found inside value ranges, then the ranges' ends are joined.
    """
    v = points.where(F.col(value).isNotNull()).select(F.col(value).cast("double").alias("v")).distinct()
    span = (hi - lo) or 1.0
    cell = F.least(F.greatest(F.floor((F.col("v") - lo) / F.lit(span) * 256), F.lit(0)), F.lit(255))
    ranges = v.withColumn("cell", cell)
    w = Window.partitionBy("cell").orderBy("v")
    inner = ranges.withColumn("gap", (F.lead("v").over(w) - F.col("v")) / 2).agg(F.max("gap").alias("g"))
    ends = ranges.groupBy("cell").agg(F.min("v").alias("first"), F.max("v").alias("last"))
    between = ends.withColumn("gap", (F.lead("first").over(Window.orderBy("cell")) - F.col("last")) / 2)  # at most 256 rows
    outer = between.agg(F.max("gap").alias("g"), (F.min("first") - lo).alias("low"), (hi - F.max("last")).alias("high"))
    return inner.crossJoin(outer.withColumnRenamed("g", "g2")).select(F.greatest("g", "g2", "low", "high").alias("radius"))


def covering_exact_2d(x: np.ndarray) -> float:
    """Exact radius in the unit square: each point's cell is clipped by its neighbours until the next one is too far to cut it."""
    worst = 0.0
    for i in range(len(x)):
        d2 = ((x - x[i]) ** 2).sum(axis=1)
        cell = np.array([[0.0, 0.0], [1.0, 0.0], [1.0, 1.0], [0.0, 1.0]])
        far = ((cell - x[i]) ** 2).sum(axis=1).max()
        for j in np.argsort(d2):
            if d2[j] == 0:
                continue
            if d2[j] > 4 * far:
                break
            normal, middle = x[j] - x[i], (x[i] + x[j]) / 2
            side = (cell - middle) @ normal
            if (side <= 0).all():
                continue
            kept = []
            for k in range(len(cell)):
                a, b, sa, sb = cell[k - 1], cell[k], side[k - 1], side[k]
                if (sa <= 0) != (sb <= 0):
                    kept.append(a + (b - a) * sa / (sa - sb))
                if sb <= 0:
                    kept.append(b)
            cell = np.array(kept)
            far = ((cell - x[i]) ** 2).sum(axis=1).max()
        worst = max(worst, far)
    return float(np.sqrt(worst))


#: Vertices that are solved for at once.
SOLVE = 20_000


def _cell_radius_sq(x: np.ndarray, i: int, near: list[int]) -> float:
    """Squared distance from point i to the farthest vertex of its cell, cut by the bisectors with ``near`` and the cube's faces."""
    from itertools import combinations, islice

    n = x.shape[1]
    normals = np.concatenate([x[near] - x[i], -np.eye(n), np.eye(n)])
    limits = np.r_[(x[near] ** 2).sum(axis=1) / 2 - (x[i] @ x[i]) / 2, np.zeros(n), np.ones(n)]
    picks, worst = combinations(range(len(normals)), n), 0.0
    while block := list(islice(picks, SOLVE)):
        at = np.array(block)
        m = normals[at]
        good = np.abs(np.linalg.det(m)) > 1e-12
        if not good.any():
            continue
        p = np.linalg.solve(m[good], limits[at[good]][..., None])[..., 0]
        inside = (p @ normals.T <= limits + 1e-9).all(axis=1)
        if inside.any():
            worst = max(worst, float(((p[inside] - x[i]) ** 2).sum(axis=1).max()))
    return worst


def covering_exact_nd(x: np.ndarray) -> float:
    """Exact radius in the unit cube: the farthest vertex of any point's cell.

    A cell is cut by its nearest points; more are taken until the next one is
    too far to cut it. Vertices are intersections of n planes, so this is meant
    for up to five axes and some hundred points; two axes are clipped instead.
    """
    n, worst = x.shape[1], 0.0
    if n == 2:
        return covering_exact_2d(x)
    for i in range(len(x)):
        d2 = ((x - x[i]) ** 2).sum(axis=1)
        near = [j for j in np.argsort(d2, kind="stable").tolist() if d2[j] > 0]
        size = min(len(near), 4 * n)
        while True:
            value = _cell_radius_sq(x, i, near[:size])
            if size == len(near) or d2[near[size]] > 4 * value:
                break
            size = min(len(near), size + 2 * n)
        worst = max(worst, value)
    return float(np.sqrt(worst))


def upper_np(x: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> float:
    return float(np.sqrt((np.maximum(x - lo, hi - x) ** 2).sum(axis=1).max()))


def upper_in_boxes_np(x: np.ndarray, box: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> float:
    """Upper bound from the points x in the boxes numbered ``box``; a box without a point is reached from the one that covers it best."""
    upper = upper_np(x, lo[box], hi[box])
    for k in np.setdiff1d(np.arange(len(lo)), box):
        upper = max(upper, float(np.sqrt((np.maximum(x - lo[k], hi[k] - x) ** 2).sum(axis=1).min())))
    return upper


def lower_np(x: np.ndarray, m: int, *key: int) -> float:
    p = rng.fast_uniform(*key, 31, np.arange(m)[:, None], np.arange(x.shape[1])[None, :])
    return float(np.sqrt(max(min_distance_sq(p[k : k + 512], x).max() for k in range(0, m, 512))))


def bound_tightness(rows: DataFrame, eps: float = 1e-9) -> DataFrame:
    """Share of rows (n, exact, upper) per n whose upper bound is exact, within ``eps`` and bit by bit."""
    share = lambda same: F.avg(same.cast("double"))
    close, equal = F.abs(F.col("exact") - F.col("upper")) < eps, F.col("exact") == F.col("upper")
    return rows.groupBy("n").agg(share(close).alias("tight"), share(equal).alias("equal"), F.avg(F.col("upper") / F.col("exact")).alias("mean_ratio"))


def separation(points: DataFrame, n: int, point_id: str = "point_id", x: str = "x") -> DataFrame:
    """Smallest distance between two points of the unit cube, one row (null below two points).

    A first bound comes from neighbours in space-filling cells; then only points
    in the same or adjoining cells of that size are compared.
    """
    chosen = points.where(F.col(x).isNotNull()).select(F.col(point_id).alias("id"), F.col(x).alias("x"))
    total = chosen.count()
    if total < 2:
        return points.sparkSession.createDataFrame([(None,)], "separation double")
    k = max(1, planner.integer_root(total, n))
    axes = [F.least(F.greatest(F.floor(F.element_at("x", d + 1) * k), F.lit(0)), F.lit(k - 1)) for d in range(n)]
    w = Window.partitionBy(*axes).orderBy("id")
    near = chosen.withColumn("next", F.lead("x").over(w)).where("next is not null").agg(F.min(F.sqrt(distance_sq(F.col("x"), F.col("next")))).alias("d")).first().d
    side = near if near is not None else n**0.5
    if side == 0:
        return points.sparkSession.createDataFrame([(0.0,)], "separation double")
    cells = min(1 << 20, max(1, int(1 / side)))
    home = [F.floor(F.element_at("x", d + 1) * cells).cast("long") for d in range(n)]
    here = chosen.withColumn("cell", F.array(*home))
    moves = np.stack(np.meshgrid(*[[-1, 0, 1]] * n), axis=-1).reshape(-1, n).tolist()
    around = here.withColumn("move", F.explode(F.array(*[F.array(*[F.lit(v) for v in m]) for m in moves])))
    around = around.select(F.col("id").alias("id2"), F.col("x").alias("x2"), F.zip_with("cell", "move", lambda c, m: c + m).alias("cell"))
    pairs = here.join(around, "cell").where("id < id2")
    return pairs.agg(F.least(F.min(F.sqrt(distance_sq(F.col("x"), F.col("x2")))), F.lit(near)).alias("separation"))
