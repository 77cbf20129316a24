"""Equal-volume strata by count-proportional two-way splits, and by grids.

A leaf needs no state to be found: its number, compared with the counts on the
way down, names its box. So strata are a projection of ``spark.range``, a point
finds its stratum by the same descent, and neither shuffles anything. Very
large partitions ship subtree roots instead and expand them with NumPy.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import rng
from ..plans import counts, planner

MODES = ("fixed", "keyed")


def _bounds(n: int, lo: Sequence[float] | None, hi: Sequence[float] | None) -> tuple[list[float], list[float]]:
    low, high = [float(v) for v in (lo or [0.0] * n)], [float(v) for v in (hi or [1.0] * n)]
    if len(low) != n or len(high) != n or any(a > b for a, b in zip(low, high)):
        raise ValueError("bounds must be n pairs with lo <= hi")
    return low, high


def _check(count: int, n: int, mode: str) -> None:
    if count < 1 or n < 1:
        raise ValueError("count and dims must be positive")
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")


def _descent(count: int, n: int, avoid_odd: bool, mode: str, seed: int, lo: list[float], hi: list[float], goes_left) -> Column:
    """The struct (lo, hi, cnt, off) of the leaf that ``goes_left(state, axis, cut, share)`` leads to."""
    array = lambda v: F.array(*[F.lit(x) for x in v])
    state = F.struct(array(lo).alias("lo"), array(hi).alias("hi"), F.lit(count).cast("long").alias("cnt"), F.lit(0).cast("long").alias("off"))

    def step(s: Column, _: Column) -> Column:
        share = counts.smaller_share_col(s.cnt, avoid_odd).cast("long")
        sides = F.zip_with(s.hi, s.lo, lambda h, low: h - low)
        longest = F.array_max(sides) * (1 - counts.TIE)
        if mode == "fixed":
            axis = F.array_position(F.transform(sides, lambda x: x >= longest), True)
        else:
            share = F.when(rng.uniform(seed, "swap", s.off, s.cnt) < 0.5, share).otherwise(s.cnt - share)
            ties = F.filter(F.sequence(F.lit(1), F.lit(n)), lambda k: F.element_at(sides, k) >= longest)
            pick = F.floor(rng.uniform(seed, "axis", s.off, s.cnt) * F.size(ties)).cast("int")
            axis = F.element_at(ties, pick + 1).cast("long")
        low, high = F.element_at(s.lo, axis.cast("int")), F.element_at(s.hi, axis.cast("int"))
        cut = low + (high - low) * share.cast("double") / s.cnt.cast("double")
        left = goes_left(s, axis, cut, share)
        put = lambda side: F.transform(side, lambda v, k: F.when(k + 1 == axis, cut).otherwise(v))
        moved = F.struct(
            F.when(left, s.lo).otherwise(put(s.lo)).alias("lo"),
            F.when(left, put(s.hi)).otherwise(s.hi).alias("hi"),
            F.when(left, share).otherwise(s.cnt - share).alias("cnt"),
            F.when(left, s.off).otherwise(s.off + share).alias("off"),
        )
        return F.when(s.cnt == 1, s).otherwise(moved)

    levels = counts.depth(count, avoid_odd)
    return F.aggregate(F.sequence(F.lit(1), F.lit(levels)), state, step) if levels else state


def leaf_box(leaf: Column, count: int, n: int, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0, lo=None, hi=None) -> Column:
    """struct(lo, hi, cnt, off) of leaf number ``leaf``."""
    _check(count, n, mode)
    low, high = _bounds(n, lo, hi)
    return _descent(count, n, avoid_odd, mode, seed, low, high, lambda s, axis, cut, share: leaf < s.off + share)


#: Leaves up to which a point's way down is compiled into nested comparisons, and up to which the tree travels as literal arrays.
CASE_LEAVES, TREE_LEAVES = 256, 20_000


def split_tree(count: int, n: int, avoid_odd: bool, mode: str, seed: int, lo: list[float], hi: list[float]) -> tuple[list[int], list[float], list[int], list[int]]:
    """(axis, cut, below, above) per inner node, root first; children are inner node numbers or ``-1 - leaf``."""
    axis, cut, below, above = [], [], [], []
    todo = [(0, count, lo, hi, -1, False)]
    while todo:
        off, cnt, low, high, parent, upper = todo.pop()
        name = len(axis) if cnt > 1 else -1 - off
        if parent >= 0:
            (above if upper else below)[parent] = name
        if cnt == 1:
            continue
        share = counts.smaller_share(cnt, avoid_odd)
        sides = [h - v for v, h in zip(low, high)]
        tied = [k for k, side in enumerate(sides) if side >= max(sides) * (1 - counts.TIE)]
        d = tied[0]
        if mode == "keyed":
            share = share if rng.uniform_py(seed, "swap", off, cnt) < 0.5 else cnt - share
            d = tied[int(rng.uniform_py(seed, "axis", off, cnt) * len(tied))]
        at = low[d] + sides[d] * float(share) / float(cnt)
        axis.append(d)
        cut.append(at)
        below.append(0)
        above.append(0)
        left_high, right_low = [*high[:d], at, *high[d + 1 :]], [*low[:d], at, *low[d + 1 :]]
        todo += [(off + share, cnt - share, right_low, high, name, True), (off, share, low, left_high, name, False)]
    return axis, cut, below, above


def tree_boxes_np(count: int, n: int, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(lo, hi) of all strata of a small tree in the unit cube, in leaf order; keyed mode draws from md5 keys, as descents do."""
    axis, cut, below, above = split_tree(count, n, avoid_odd, mode, seed, [0.0] * n, [1.0] * n)
    lo, hi = np.zeros((count, n)), np.ones((count, n))
    todo = [(0 if axis else -1, np.zeros(n), np.ones(n))]
    while todo:
        node, low, high = todo.pop()
        if node < 0:
            lo[-1 - node], hi[-1 - node] = low, high
            continue
        left_high, right_low = high.copy(), low.copy()
        left_high[axis[node]] = right_low[axis[node]] = cut[node]
        todo += [(below[node], low, left_high), (above[node], right_low, high)]
    return lo, hi


def descend_np(x: np.ndarray, count: int, n: int, avoid_odd: bool, lo: list[float], hi: list[float]) -> np.ndarray:
    """Stratum of every point in fixed mode, level by level for all points at once."""
    low, high = np.tile(lo, (len(x), 1)), np.tile(hi, (len(x), 1))
    cnt, off, row = np.full(len(x), count), np.zeros(len(x), np.int64), np.arange(len(x))
    while (cnt > 1).any():
        sides = high - low
        axis = (sides >= sides.max(axis=1, keepdims=True) * (1 - counts.TIE)).argmax(axis=1)
        share = counts.smaller_share_np(cnt, avoid_odd)
        cut = low[row, axis] + sides[row, axis] * share / cnt
        open_ = cnt > 1
        left = open_ & (x[row, axis] < cut)
        right = open_ & ~left
        high[row[left], axis[left]] = cut[left]
        low[row[right], axis[right]] = cut[right]
        off = np.where(right, off + share, off)
        cnt = np.where(left, share, np.where(right, cnt - share, cnt))
    return off


def stratum_of(x: Column, count: int, n: int, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0, lo=None, hi=None) -> Column:
    """Stratum number of a point (array column); a cut belongs to the upper side, points outside to the nearest edge's box.

    Null points and points with a null or not-a-number coordinate get null.
    Small trees become nested comparisons inside generated code, middling ones
    lookups in literal arrays, large fixed ones a vectorised descent.
    """
    _check(count, n, mode)
    low, high = _bounds(n, lo, hi)
    known = x.isNotNull() & ~F.exists(x, lambda v: v.isNull() | F.isnan(v))
    if count == 1:
        return F.when(known, F.lit(0).cast("long"))
    if count <= TREE_LEAVES:
        axis, cut, below, above = split_tree(count, n, avoid_odd, mode, seed, low, high)
        if count <= CASE_LEAVES:

            def branch(node: int) -> Column:
                if node < 0:
                    return F.lit(-1 - node).cast("long")
                return F.when(F.element_at(x, axis[node] + 1) < cut[node], branch(below[node])).otherwise(branch(above[node]))

            return F.when(known, branch(0))
        literal = lambda v, kind: F.lit(np.array(v, kind).tolist())
        axes, cuts, lows, highs = literal(axis, int), literal(cut, float), literal(below, int), literal(above, int)
        at = lambda a, k: F.element_at(a, (k + 1).cast("int"))
        step = lambda node, _: F.when(node < 0, node).otherwise(F.when(F.element_at(x, at(axes, node) + 1) < at(cuts, node), at(lows, node)).otherwise(at(highs, node)).cast("long"))
        levels = F.sequence(F.lit(1), F.lit(counts.depth(count, avoid_odd)))
        return F.when(known, -1 - F.aggregate(levels, F.lit(0).cast("long"), step))
    if mode == "fixed":

        @F.pandas_udf("long")
        def descend(points: pd.Series) -> pd.Series:
            full = points.map(lambda v: v is not None and len(v) == n and bool(np.isfinite(v).all()))
            out = pd.Series(pd.array([None] * len(points), "Int64"), index=points.index)
            if full.any():
                out[full] = descend_np(np.stack(points[full].to_numpy()), count, n, avoid_odd, low, high)
            return out

        return F.when(known, descend(F.when(known, x)))
    found = _descent(count, n, avoid_odd, mode, seed, low, high, lambda s, axis, cut, share: F.element_at(x, axis.cast("int")) < cut)
    return F.when(known, found.off)


def expand_np(count: np.ndarray, off: np.ndarray, lo: np.ndarray, hi: np.ndarray, avoid_odd: bool, mode: str, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(off, lo, hi) of all leaves below the given nodes, level by level; keyed choices hash (offset, count)."""
    done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    while len(count):
        leaf = count == 1
        if leaf.any():
            done.append((off[leaf], lo[leaf], hi[leaf]))
            count, off, lo, hi = count[~leaf], off[~leaf], lo[~leaf], hi[~leaf]
            if not len(count):
                break
        share = counts.smaller_share_np(count, avoid_odd)
        sides = hi - lo
        tied = sides >= sides.max(axis=1, keepdims=True) * (1 - counts.TIE)
        if mode == "fixed":
            axis = tied.argmax(axis=1)
        else:
            share = np.where(rng.fast_uniform(seed, 1, off, count) < 0.5, share, count - share)
            nth = np.floor(rng.fast_uniform(seed, 2, off, count) * tied.sum(axis=1)).astype(int)
            axis = (np.cumsum(tied, axis=1) > nth[:, None]).argmax(axis=1)
        row = np.arange(len(count))
        cut = lo[row, axis] + sides[row, axis] * share / count
        left_hi, right_lo = hi.copy(), lo.copy()
        left_hi[row, axis] = cut
        right_lo[row, axis] = cut
        count, off = np.r_[share, count - share], np.r_[off, off + share]
        lo, hi = np.concatenate([lo, right_lo]), np.concatenate([left_hi, hi])
    if not done:
        return np.empty(0, np.int64), lo, hi
    return tuple(np.concatenate(x) for x in zip(*done))  # type: ignore[return-value]


def bsplit_np(count: int, n: int, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0, lo=None, hi=None) -> tuple[np.ndarray, np.ndarray]:
    """(lo, hi) of all strata in leaf order."""
    _check(count, n, mode)
    low, high = _bounds(n, lo, hi)
    off, a, b = expand_np(np.array([count]), np.array([0]), np.array([low]), np.array([high]), avoid_odd, mode, seed)
    order = np.argsort(off)
    return a[order], b[order]


STRATA = "stratum_id long, lo array<double>, hi array<double>, cnt long"


def bsplit_strata(spark: SparkSession, count: int, n: int, lo=None, hi=None, avoid_odd: bool = True, mode: str = "fixed", seed: int = 0, engine: str | None = None) -> DataFrame:
    """(stratum_id, lo, hi, cnt): ``count`` boxes of equal volume.

    ``engine``: ``descent`` computes each leaf from its number, ``subtree``
    expands shipped subtree roots with NumPy, ``levels`` splits a frontier of
    nodes round by round. In keyed mode ``descent`` and ``levels`` draw from md5
    keys, ``subtree`` from mixed integers: equally random, not the same boxes.
    """
    _check(count, n, mode)
    low, high = _bounds(n, lo, hi)
    engine = engine or planner.strata_engine(count)
    if engine == "descent":
        box = leaf_box(F.col("id"), count, n, avoid_odd, mode, seed, low, high)
        return spark.range(count).withColumn("b", box).select(F.col("id").alias("stratum_id"), "b.lo", "b.hi", "b.cnt")
    if engine == "levels":
        return _by_levels(spark, count, n, low, high, avoid_odd, mode, seed)
    if engine != "subtree":
        raise ValueError(f"unknown engine {engine!r}")
    parallel = spark.sparkContext.defaultParallelism
    roots = _frontier_nodes(count, low, high, 16 * parallel, avoid_odd, mode, seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                yield from _leaves(row["off"], row["cnt"], row["lo"], row["hi"], avoid_odd, mode, seed)

    frame = spark.createDataFrame(roots, "off long, cnt long, lo array<double>, hi array<double>").repartition(min(len(roots), 4 * parallel), "off")
    return frame.mapInArrow(run, STRATA)


#: Leaves that a task expands at once.
CHUNK = 1 << 16


def _leaves(off: int, cnt: int, lo: list[float], hi: list[float], avoid_odd: bool, mode: str, seed: int) -> Iterator[pa.RecordBatch]:
    """Batches of leaves under a node; subtrees are opened depth first so that memory stays bounded."""
    stack = [(off, cnt, lo, hi)]
    while stack:
        off, cnt, lo, hi = stack.pop()
        if cnt > CHUNK:
            stack += reversed(_children(off, cnt, lo, hi, avoid_odd, mode, seed))
            continue
        ids, a, b = expand_np(np.array([cnt]), np.array([off]), np.array([lo]), np.array([hi]), avoid_odd, mode, seed)
        order = np.argsort(ids)
        ends = pa.array(np.arange(len(ids) + 1) * a.shape[1], pa.int32())
        box = [pa.ListArray.from_arrays(ends, pa.array(side[order].ravel())) for side in (a, b)]
        yield pa.RecordBatch.from_arrays([pa.array(ids[order]), *box, pa.array(np.ones(len(ids), np.int64))], names=["stratum_id", "lo", "hi", "cnt"])


def _children(off: int, cnt: int, lo: list[float], hi: list[float], avoid_odd: bool, mode: str, seed: int) -> list[tuple]:
    share = counts.smaller_share(cnt, avoid_odd)
    sides = [h - low for low, h in zip(lo, hi)]
    tied = [k for k, s in enumerate(sides) if s >= max(sides) * (1 - counts.TIE)]
    axis = tied[0]
    if mode == "keyed":
        share = share if rng.fast_uniform(seed, 1, off, cnt) < 0.5 else cnt - share
        axis = tied[int(rng.fast_uniform(seed, 2, off, cnt) * len(tied))]
    cut = lo[axis] + sides[axis] * share / cnt
    upper, lower = list(hi), list(lo)
    upper[axis] = lower[axis] = cut
    return [(off, share, lo, upper), (off + share, cnt - share, lower, hi)]


def _frontier_nodes(count: int, lo: list[float], hi: list[float], wanted: int, avoid_odd: bool, mode: str, seed: int) -> list[tuple]:
    nodes = [(0, count, lo, hi)]
    while len(nodes) < wanted and any(c > 1 for _, c, *_ in nodes):
        nodes = [child for node in nodes for child in (_children(*node, avoid_odd, mode, seed) if node[1] > 1 else [node])]
    return nodes


def _by_levels(spark: SparkSession, count: int, n: int, lo: list[float], hi: list[float], avoid_odd: bool, mode: str, seed: int) -> DataFrame:
    """The whole tree in rounds: each turns every open node into two rows."""
    nodes = spark.createDataFrame([(0, count, lo, hi)], "off long, cnt long, lo array<double>, hi array<double>")
    for _ in range(counts.depth(count, avoid_odd)):
        share = counts.smaller_share_col(F.col("cnt"), avoid_odd).cast("long")
        if mode == "keyed":
            share = F.when(rng.uniform(seed, "swap", F.col("off"), F.col("cnt")) < 0.5, share).otherwise(F.col("cnt") - share)
        side = F.when(F.col("cnt") > 1, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(2)))
        sides = F.zip_with("hi", "lo", lambda h, low: h - low)
        open_ = nodes.withColumns({"share": share, "sides": sides}).withColumn("longest", F.array_max("sides") * (1 - counts.TIE))
        if mode == "fixed":
            axis = F.array_position(F.transform("sides", lambda x: x >= F.col("longest")), True).cast("int")
        else:
            ties = F.filter(F.sequence(F.lit(1), F.lit(n)), lambda k: F.element_at(F.col("sides"), k) >= F.col("longest"))
            axis = F.element_at(ties, F.floor(rng.uniform(seed, "axis", F.col("off"), F.col("cnt")) * F.size(ties)).cast("int") + 1)
        open_ = open_.withColumn("axis", axis)
        low, high = F.element_at("lo", F.col("axis")), F.element_at("hi", F.col("axis"))
        open_ = open_.withColumn("cut", low + (high - low) * F.col("share").cast("double") / F.col("cnt").cast("double")).withColumn("side", F.explode(side))
        put = lambda c: F.transform(c, lambda v, k: F.when(k + 1 == F.col("axis"), F.col("cut")).otherwise(v))
        pick = lambda a, b, c: F.when(F.col("side") == 0, a).when(F.col("side") == 1, b).otherwise(c)
        nodes = open_.select(
            pick(F.col("off"), F.col("off") + F.col("share"), F.col("off")).alias("off"),
            pick(F.col("share"), F.col("cnt") - F.col("share"), F.col("cnt")).alias("cnt"),
            pick(F.col("lo"), put("lo"), F.col("lo")).alias("lo"),
            pick(put("hi"), F.col("hi"), F.col("hi")).alias("hi"),
        )
    return nodes.select(F.col("off").alias("stratum_id"), "lo", "hi", "cnt")


def grid_strata(spark: SparkSession, ks: Sequence[int]) -> DataFrame:
    """Cells of a grid with ``ks[d]`` equal parts along axis d; axis 0 varies fastest."""
    if not ks or any(k < 1 for k in ks):
        raise ValueError("every axis needs at least one part")
    total, digits, step = 1, [], 1
    for k in ks:
        digits.append(F.pmod(F.floor(F.col("id") / step), F.lit(k)).cast("double"))
        step *= k
    total = step
    lo = F.array(*[d / float(k) for d, k in zip(digits, ks)])
    hi = F.array(*[(d + 1) / float(k) for d, k in zip(digits, ks)])
    return spark.range(total).select(F.col("id").alias("stratum_id"), lo.alias("lo"), hi.alias("hi"), F.lit(1).cast("long").alias("cnt"))


def grid_np(k: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    digit = (np.arange(k**n)[:, None] // k ** np.arange(n)) % k
    return digit / k, (digit + 1) / k


def auto_strata(spark: SparkSession, count: int, n: int, **how) -> DataFrame:
    """An equal grid where ``count`` is a power that fits ``n``, else two-way splits."""
    if planner.stratifier(count, n) == "grid":
        return grid_strata(spark, [planner.integer_root(count, n)] * n)
    return bsplit_strata(spark, count, n, **how)


def side_ratio(strata: DataFrame) -> DataFrame:
    """One row: shortest over longest side, least over all strata."""
    sides = F.zip_with("hi", "lo", lambda h, low: h - low)
    return strata.agg(F.min(F.array_min(sides) / F.array_max(sides)).alias("side_ratio"))


def volume(lo: Column, hi: Column) -> Column:
    return F.aggregate(F.zip_with(hi, lo, lambda h, low: h - low), F.lit(1.0), lambda acc, s: acc * s)
