"""Partitions fitted to points that already exist, and uniform subsets picked with them."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import rng
from ..plans.checkpoints import durable
from . import covering

RULES = ("middle", "median", "mean", "mean_gap")

#: Points below which a box is finished inside one task.
LOCAL_POINTS = 50_000


def _gap_cut(values: np.ndarray) -> float:
    """Midway between the members next to the mean."""
    mean = values.mean()
    below, above = values[values <= mean], values[values > mean]
    if not len(above):  # rounding of the mean
        top = values.max()
        below, above = values[values < top], values[values == top]
    return float((below.max() + above.min()) / 2)


def mean_gap_np(x: np.ndarray, lo: np.ndarray, hi: np.ndarray, *key: int) -> tuple[np.ndarray, np.ndarray]:
    """(lo, hi) of the box of every point; equal points share a box."""
    low, high = np.tile(lo, (len(x), 1)).astype(float), np.tile(hi, (len(x), 1)).astype(float)
    stack = [(np.arange(len(x)), lo.astype(float), hi.astype(float), 1)]
    while stack:
        member, a, b, node = stack.pop()
        if len(member) == 1:
            low[member[0]], high[member[0]] = a, b
            continue
        mine = x[member]
        spread = mine.max(axis=0) > mine.min(axis=0)
        if not spread.any():
            low[member], high[member] = a, b
            continue
        side = np.where(spread, b - a, -np.inf)
        tied = np.flatnonzero(side >= side.max() * (1 - 1e-12))
        axis = int(tied[0]) if len(tied) == 1 else int(tied[int(rng.fast_uniform(*key, 41, node % (1 << 62)) * len(tied))])
        v = mine[:, axis]
        cut = _gap_cut(v)
        left = v <= cut
        if left.all() or not left.any():  # neighbours too close for a midpoint
            cut = float(v.min())
            left = v <= cut
        upper, lower = b.copy(), a.copy()
        upper[axis] = lower[axis] = cut
        stack += [(member[left], a, upper, 2 * node), (member[~left], lower, b, 2 * node + 1)]
    return low, high


def mean_gap_partition(points: DataFrame, n: int, tries: int = 1, seed: int = 0, point_id: str = "point_id", x: str = "x") -> DataFrame:
    """(try, point_id, x, lo, hi): boxes with one point (or equal points) each, covering the unit cube.

    While a box holds too many points for a task, whole levels are cut by
    aggregates: members' mean on the longest side that has a spread, then the
    neighbours on either side of it, then the cut between them. Small boxes are
    finished in tasks of their own. Rows with a null point take no part.
    """
    chosen = points.where(F.col(x).isNotNull() & ~F.exists(x, lambda v: v.isNull())).select(F.col(point_id).alias("point_id"), F.col(x).alias("x"))
    zero, one = F.array(*[F.lit(0.0)] * n), F.array(*[F.lit(1.0)] * n)
    rows = chosen.select(F.explode(F.sequence(F.lit(0), F.lit(tries - 1))).alias("try"), "point_id", "x", zero.alias("lo"), one.alias("hi"), F.lit(1).cast("long").alias("node"))
    spread = lambda d: F.min(F.element_at("x", d + 1)) < F.max(F.element_at("x", d + 1))
    several = reduce(lambda p, q: p | q, [spread(d) for d in range(n)])
    while True:
        big = durable(rows.groupBy("try", "node").agg(F.count("*").alias("count"), several.alias("several")).where(F.col("count") > LOCAL_POINTS))
        if not big.where("several").limit(1).count():
            break
        rows = _cut_level(rows, big.where("several").drop("several"), n, seed)
    # a large box that is left holds equal points only, and is done
    same = F.broadcast(big.select("try", "node"))
    done = rows.join(same, ["try", "node"], "left_semi").select("try", "point_id", "x", "lo", "hi")
    rows = rows.join(same, ["try", "node"], "left_anti")

    schema = "try int, point_id " + chosen.schema["point_id"].dataType.simpleString() + ", x array<double>, lo array<double>, hi array<double>"

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pts = np.stack(pdf["x"].to_numpy())
        a, b = np.array(pdf["lo"].iloc[0]), np.array(pdf["hi"].iloc[0])
        low, high = mean_gap_np(pts, a, b, seed, int(pdf["try"].iloc[0]), int(pdf["node"].iloc[0]))
        return pdf[["try", "point_id", "x"]].assign(lo=list(low), hi=list(high))

    return rows.groupBy("try", "node").applyInPandas(run, schema).unionByName(done)


def _cut_level(rows: DataFrame, big: DataFrame, n: int, seed: int) -> DataFrame:
    """Cuts every box named in ``big``, one row for ``LOCAL_POINTS`` points or more, once; boxes and cuts are broadcast."""
    at = lambda c, d: F.element_at(c, d + 1)
    open_ = rows.join(F.broadcast(big.drop("count")), ["try", "node"], "left_semi")
    ranges = open_.groupBy("try", "node").agg(F.first("lo").alias("lo"), F.first("hi").alias("hi"), *[F.min(at("x", d)).alias(f"a{d}") for d in range(n)], *[F.max(at("x", d)).alias(f"b{d}") for d in range(n)], *[F.avg(at("x", d)).alias(f"m{d}") for d in range(n)])
    side = F.array(*[F.when(F.col(f"b{d}") > F.col(f"a{d}"), at("hi", d) - at("lo", d)).otherwise(F.lit(-1.0)) for d in range(n)])
    turn = F.filter(F.sequence(F.lit(1), F.lit(n)), lambda k: F.element_at(F.col("side"), k) >= F.array_max("side") * (1 - 1e-12))
    axes = ranges.withColumn("side", side).where(F.array_max("side") > 0)
    axes = axes.withColumn("axis", F.element_at(turn, F.floor(rng.uniform(seed, "fit", F.col("try"), F.col("node")) * F.size(turn)).cast("int") + 1))
    of = lambda c: F.element_at(F.array(*[F.col(f"{c}{d}") for d in range(n)]), F.col("axis"))
    axes = axes.withColumns({"mean": of("m"), "top": of("b")}).select("try", "node", "axis", "mean", "top")
    valued = open_.join(F.broadcast(axes), ["try", "node"]).withColumn("v", F.element_at("x", F.col("axis")))
    # where rounding puts the mean at the top, the neighbours are the top and the next
    mid = F.least("mean", "below")
    valued = valued.join(F.broadcast(valued.where("v < top").groupBy("try", "node").agg(F.max("v").alias("below"))), ["try", "node"])
    cuts = valued.groupBy("try", "node", "axis").agg(F.max(F.when(F.col("v") <= mid, F.col("v"))).alias("p"), F.min(F.when(F.col("v") > mid, F.col("v"))).alias("q"))
    middle = (F.col("p") + F.col("q")) / 2
    cuts = cuts.select("try", "node", "axis", F.when(middle < F.col("q"), middle).otherwise(F.col("p")).alias("cut"))
    joined = rows.join(F.broadcast(cuts), ["try", "node"], "left")
    left = F.element_at("x", F.col("axis")) <= F.col("cut")
    put = lambda c: F.transform(c, lambda v, k: F.when(k + 1 == F.col("axis"), F.col("cut")).otherwise(v))
    return durable(
        joined.select(
            "try",
            "point_id",
            "x",
            F.when(F.col("axis").isNull() | left, F.col("lo")).otherwise(put("lo")).alias("lo"),
            F.when(F.col("axis").isNull() | ~left, F.col("hi")).otherwise(put("hi")).alias("hi"),
            F.when(F.col("axis").isNull(), F.col("node")).when(left, F.col("node") * 2).otherwise(F.col("node") * 2 + 1).alias("node"),
        )
    )


def covering_upper_fitted(points: DataFrame, n: int, tries: int = 10, seed: int = 0, point_id: str = "point_id", x: str = "x") -> DataFrame:
    """Upper bound of the covering radius of any point set: the best of several fitted partitions, one row."""
    boxed = mean_gap_partition(points, n, tries, seed, point_id, x)
    each = boxed.groupBy("try").agg(F.max(covering.corner_distance(F.col("x"), F.col("lo"), F.col("hi"))).alias("upper"))
    return each.agg(F.min("upper").alias("upper"))


def fitted_upper_np(x: np.ndarray, tries: int, *key: int) -> float:
    n = x.shape[1]
    bounds = (mean_gap_np(x, np.zeros(n), np.ones(n), *key, t) for t in range(tries))
    return min(covering.upper_np(x, lo, hi) for lo, hi in bounds)


def _cut(values: np.ndarray, low: float, high: float, rule: str) -> float:
    if rule == "middle":
        return (low + high) / 2
    if rule == "median":
        return float(np.median(values))
    return _gap_cut(values) if rule == "mean_gap" else float(values.mean())


def pick_np(x: np.ndarray, m: int, rule: str = "middle", *key: int) -> np.ndarray:
    """Rows of a subset of m members: the box with the widest side is split until m boxes hold members; each gives the member nearest its middle."""
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")
    import heapq

    heap: list = []
    order = 0

    def push(member: np.ndarray) -> None:
        nonlocal order
        # boxes shrink to their members, so every middle cut has members on both sides
        width = float((x[member].max(axis=0) - x[member].min(axis=0)).max())
        heapq.heappush(heap, (-width, order, member))
        order += 1

    if len(x):
        push(np.arange(len(x)))
    while heap and len(heap) < m and heap[0][0] < 0:
        _, _, member = heapq.heappop(heap)
        low, high = x[member].min(axis=0), x[member].max(axis=0)
        axis = int((high - low).argmax())
        v = x[member, axis]
        left = v <= _cut(v, float(low[axis]), float(high[axis]), rule)
        if left.all():
            left = v < high[axis]
        push(member[left])
        push(member[~left])
    out = []
    for _, _, member in heap:
        middle = (x[member].min(axis=0) + x[member].max(axis=0)) / 2
        out.append(int(member[((x[member] - middle) ** 2).sum(axis=1).argmin()]))
    return np.array(sorted(out), np.int64)


def select_uniform_subset(points: DataFrame, m: int, n: int, rule: str = "middle", point_id: str = "point_id", x: str = "x", parts: int | None = None) -> DataFrame:
    """About uniform subset of ``m`` rows (all, if fewer distinct points).

    The unit cube is first cut into equal strata of which none should hold more
    than a task can take; each stratum's quota follows its share of the filled
    cells at a finer level, then members are picked inside the stratum.
    """
    from .strata import stratum_of

    chosen = points.where(F.col(x).isNotNull() & ~F.exists(x, lambda v: v.isNull())).select(F.col(point_id).alias("point_id"), F.col(x).alias("x"))
    total = chosen.count()
    parts = parts or max(1, -(-total // LOCAL_POINTS))
    placed = chosen.withColumn("part", stratum_of(F.col("x"), parts, n) if parts > 1 else F.lit(0).cast("long"))
    fine = placed.withColumn("cell", stratum_of(F.col("x"), max(parts, 4 * m), n))
    filled = fine.groupBy("part").agg(F.count_distinct("cell").alias("cells"), F.count_distinct("x").alias("most"))
    quota = _quotas([(r.part, r.cells, r.most) for r in filled.orderBy("part").collect()], m)  # one row per part
    quotas = points.sparkSession.createDataFrame(list(quota.items()) or [(0, 0)], "part long, quota long")
    dealt = placed.join(F.broadcast(quotas), "part").where("quota > 0")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("point_id", ignore_index=True)
        rows = pick_np(np.stack(pdf["x"].to_numpy()), int(pdf["quota"].iloc[0]), rule)
        return pdf.loc[rows, ["point_id", "x"]]

    return dealt.groupBy("part").applyInPandas(run, chosen.schema)


def _quotas(parts: list[tuple[int, int, int]], m: int) -> dict[int, int]:
    """m shared out in proportion to filled cells, at most each part's distinct points; largest remainders first."""
    room = {p: most for p, _, most in parts}
    out = {p: 0 for p, *_ in parts}
    left = min(m, sum(room.values()))
    while left:
        open_ = [(p, cells) for p, cells, _ in parts if out[p] < room[p]]
        total = sum(c for _, c in open_)
        exact = {p: left * c / total for p, c in open_}
        give = {p: min(int(exact[p]), room[p] - out[p]) for p, _ in open_}
        if not any(give.values()):
            for p, _ in sorted(open_, key=lambda t: (-exact[t[0]], t[0]))[:left]:
                give[p] = 1
        for p, g in give.items():
            out[p] += g
            left -= g
    return out

