"""Unanchored L2 discrepancy: pair sums in tiles or blocks, a sort on the line, or sampled boxes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng
from ..plans.checkpoints import durable

#: Points of a tile's side.
TILE = 2048


def expected_sq(count: int, n: int) -> float:
    """Mean squared discrepancy of independent uniform points."""
    return 6.0**-n * (1 - 2.0**-n) / count


def discrepancy_np(x: np.ndarray) -> float:
    """Squared discrepancy of a small set by its closed form."""
    count, n = x.shape
    pairs = sum(float(_pair_sums(x[k : k + 512], x).sum()) for k in range(0, count, 512))
    singles = float((x * (1 - x)).prod(axis=1).sum())
    return pairs / count**2 - 2.0 ** (1 - n) * singles / count + 12.0**-n


def _pair_sums(a: np.ndarray, b: np.ndarray, w: np.ndarray | None = None) -> np.ndarray:
    out = np.ones((len(a), len(b)))
    for d in range(a.shape[1]):
        p, q = a[:, d, None], b[None, :, d]
        out *= np.minimum(p, q) * (1 - np.maximum(p, q))
    return out.sum(axis=1) if w is None else out @ w


#: Points below which divide and conquer falls back to all pairs.
SMALL = 48


def _between(a: np.ndarray, wa: np.ndarray, b: np.ndarray, wb: np.ndarray) -> float:
    """Sum over a in one set and b in another of their weights times the product, over axes, of min(1 - max)."""
    if not len(a) or not len(b):
        return 0.0
    if len(a) * len(b) <= SMALL * SMALL:
        total = np.ones((len(a), len(b)))
        for d in range(a.shape[1]):
            p, q = a[:, d, None], b[None, :, d]
            total *= np.minimum(p, q) * (1 - np.maximum(p, q))
        return float(wa @ total @ wb)
    x, y = a[:, 0], b[:, 0]
    if a.shape[1] == 1:
        # below b: x (1 - y), from sums of x; above: y (1 - x), from sums of 1 - x
        order = np.argsort(x, kind="stable")
        low = np.r_[0.0, np.cumsum((wa * x)[order])]
        high = np.r_[0.0, np.cumsum((wa * (1 - x))[order])]
        at = np.searchsorted(x[order], y, "right")
        return float((wb * ((1 - y) * low[at] + y * (high[-1] - high[at]))).sum())
    middle = np.median(np.r_[x, y])
    left, right = x <= middle, y <= middle
    if (left.all() and right.all()) or not (left.any() or right.any()):
        # all on one side: equal values, any order of them gives the same product
        if x.max() == x.min() == y.max() == y.min():
            return _between(a[:, 1:], wa * x[0], b[:, 1:], wb * (1 - x[0]))
        left, right = x < middle, y < middle
    rest = slice(1, None)
    return (
        _between(a[left], wa[left], b[right], wb[right])
        + _between(a[~left], wa[~left], b[~right], wb[~right])
        + _between(a[left][:, rest], wa[left] * x[left], b[~right][:, rest], wb[~right] * (1 - y[~right]))
        + _between(a[~left][:, rest], wa[~left] * (1 - x[~left]), b[right][:, rest], wb[right] * y[right])
    )


def discrepancy_dc_np(x: np.ndarray) -> float:
    """Squared discrepancy by divide and conquer over the axes; pays once points outnumber 2**(2n)."""
    count, n = x.shape
    one = np.ones(count)
    singles = float((x * (1 - x)).prod(axis=1).sum())
    return _between(x, one, x, one) / count**2 - 2.0 ** (1 - n) * singles / count + 12.0**-n


def discrepancy_of(x: np.ndarray) -> float:
    """The cheaper of the two exact ways."""
    return discrepancy_dc_np(x) if len(x) > max(2048, 4 ** x.shape[1]) else discrepancy_np(x)


#: Distinct points up to which all their pairs are summed in tiles; beyond, and up to so many axes, in blocks.
TILED, BLOCK_DIMS = 8192, 4

#: Points of a block, and cells that all blocks together may make.
BLOCK, CELLS = 16_384, 1 << 18


def _apart(group: np.ndarray, w: np.ndarray, side: np.ndarray, x: list[np.ndarray]) -> float:
    """Sum over pairs of one group and different ``side`` of their weights times the product, over axes, of min(1 - max)."""
    order = np.lexsort((x[0], group))
    group, w, side, x = group[order], w[order], side[order], [v[order] for v in x]
    first = np.r_[True, group[1:] != group[:-1]]
    start = np.flatnonzero(first)[np.cumsum(first) - 1]
    if len(x) == 1:
        # below: x (1 - y), from sums of x before; above: y (1 - x), the same with sides exchanged
        total = 0.0
        for a in (side, ~side):
            sums = np.r_[0.0, np.cumsum(np.where(a, w * x[0], 0.0))]
            total += float((np.where(a, 0.0, w * (1 - x[0])) * (sums[:-1] - sums[start])).sum())
        return total
    return _levels(np.arange(len(w)) - start, start, w, x, side)


def _levels(rank: np.ndarray, start: np.ndarray, w: np.ndarray, x: list[np.ndarray], side: np.ndarray | None = None) -> float:
    """Pairs of a group, by the binary digit that first tells their ranks on axis 0 apart; ``start`` numbers groups.

    The lower of a pair gives x, the upper 1 - x, which leaves one axis less.
    Without ``side`` every unordered pair counts once.
    """
    total = 0.0
    for level in range(int(rank.max(initial=0)).bit_length()):
        upper = (rank >> level & 1).astype(bool)
        node, factor = start + (rank >> level + 1), w * np.where(upper, 1 - x[0], x[0])
        # start + rank / 2**(level + 1) stays inside the group's places, so nodes of groups never meet
        if side is None:
            total += _across(node, factor, upper, x[1:])
        else:
            total += _across(2 * node + (side ^ upper), factor, side, x[1:])
    return total


def _across(group: np.ndarray, w: np.ndarray, side: np.ndarray, x: list[np.ndarray]) -> float:
    if x:
        return _apart(group, w, side, x)
    _, at = np.unique(group, return_inverse=True)
    return float((np.bincount(at, np.where(side, w, 0.0)) * np.bincount(at, np.where(side, 0.0, w))).sum())


def pairs_within(group: np.ndarray, w: np.ndarray, x: list[np.ndarray]) -> float:
    """Sum over unordered pairs of one ``group`` of their weights times the product, over axes, of min(1 - max).

    Ranks are told apart digit by digit, axis after axis, on whole arrays:
    n log(n) to the power of the axes' number.
    """
    if not len(w):
        return 0.0
    order = np.lexsort((x[0], group))
    group, w, x = group[order], w[order], [v[order] for v in x]
    first = np.r_[True, group[1:] != group[:-1]]
    start = np.flatnonzero(first)[np.cumsum(first) - 1]
    return _levels(np.arange(len(w)) - start, start, w, x)


def _far(cells: dict[str, np.ndarray], sides: int, n: int) -> float:
    """Sum over unordered pairs whose blocks differ on every axis, from the cells' sums of products of x or 1 - x."""
    total, shape = 0.0, (sides,) * n
    at = tuple(cells[f"b{d}"] for d in range(n))
    for s in range(1 << n):
        # the pair's first point is above on the axes of s, its second on the others
        one, two = np.zeros(shape), np.zeros(shape)
        np.add.at(one, at, cells[f"m{s}"])
        np.add.at(two, at, cells[f"m{(1 << n) - 1 - s}"])
        for d in range(n):
            two = np.moveaxis(two, d, 0)
            if not s >> d & 1:
                two = np.concatenate([np.cumsum(two[::-1], axis=0)[::-1][1:], np.zeros_like(two[:1])])
            else:
                two = np.concatenate([np.zeros_like(two[:1]), np.cumsum(two, axis=0)[:-1]])
            two = np.moveaxis(two, 0, d)
        total += float((one * two).sum())
    return total / 2


def _count_if(cuts: list[float], value: Column, side: str) -> Column:
    """How many of ``cuts`` are below ``value``, or equal to it."""
    return F.size(F.filter(F.lit(cuts), lambda k: k < value if side == "below" else k == value))


def _pairs_in_blocks(placed: DataFrame, count: int, n: int) -> DataFrame:
    """(pairs): the sum over all ordered pairs of ``placed`` (x0.., w), a point with itself included, by blocks of every axis.

    Blocks follow the order of an axis; values that fill several are dealt to
    them by hash, as equal values are in any order. Pairs in different blocks
    on every axis come from sums of cells; those that share a block on some are
    added block by block, and what several axes share is added and taken away
    in turn.
    """
    spark, names = placed.sparkSession, [f"x{d}" for d in range(n)]
    sides = max(2, min(-(-count // BLOCK), int(CELLS ** (1 / n) + 1e-9)))
    shares = [k / sides for k in range(1, sides)]
    cuts = placed.agg(*[F.percentile_approx(c, shares, 100 * sides).alias(c) for c in names]).first()
    for d, c in enumerate(names):
        first, equal = _count_if(cuts[c], F.col(c), "below"), _count_if(cuts[c], F.col(c), "equal")
        placed = placed.withColumn(f"b{d}", (first + F.pmod(F.xxhash64(*names, F.lit(d)), equal + 1)).cast("int"))
    moments = []
    for s in range(1 << n):
        # digit d of s: the point is the upper one on axis d
        term = F.col("w")
        for d, c in enumerate(names):
            term = term * ((1 - F.col(c)) if s >> d & 1 else F.col(c))
        moments.append(F.sum(term).alias(f"m{s}"))
    blocks = [f"b{d}" for d in range(n)]
    cells = placed.groupBy(*blocks).agg(*moments)

    def far(tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = pa.Table.from_batches(tables)
        yield pa.RecordBatch.from_arrays([pa.array([2 * _far({c: found[c].to_numpy() for c in found.column_names}, sides, n)])], names=["pairs"])

    def near(axis: int):
        def run(block: pa.Table) -> pa.Table:
            x, w = [block[c].to_numpy() for c in names], block["w"].to_numpy()
            b, total = [block[c].to_numpy().astype(np.int64) for c in blocks], 0.0
            # the sets of shared axes whose first is this one
            for s in range(1 << n - axis - 1):
                group, sign = np.zeros(len(w), np.int64), 1
                for d in range(axis + 1, n):
                    if s >> d - axis - 1 & 1:
                        group, sign = group * sides + b[d], -sign
                total += sign * pairs_within(group, w, x)
            return pa.table({"pairs": [2 * total]})

        return placed.groupBy(f"b{axis}").applyInArrow(run, "pairs double")

    own = F.col("w") * F.col("w")
    for c in names:
        own = own * F.col(c) * (1 - F.col(c))
    out = cells.repartition(1).mapInArrow(far, "pairs double").unionByName(placed.agg(F.sum(own).alias("pairs")))
    for axis in range(n):
        out = out.unionByName(near(axis))
    return out.agg(F.sum("pairs").alias("pairs"))


def _pairs_in_tiles(distinct: DataFrame, count: int, n: int) -> DataFrame:
    """(pairs): the sum over all ordered pairs of ``distinct`` (x0.., w), a point with itself included, tile i with tile j >= i."""
    names, tiles = [f"x{d}" for d in range(n)], max(1, -(-count // TILE))
    dealt = distinct.withColumn("tile", F.pmod(F.monotonically_increasing_id(), F.lit(tiles)).cast("int"))
    spread = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))))
    spread = spread.select(*names, "w", "tile", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"))

    def run(tile: pa.Table) -> pa.Table:
        i, j = tile["i"][0].as_py(), tile["j"][0].as_py()
        side, w = tile["tile"].to_numpy(), tile["w"].to_numpy()
        x = np.stack([tile[c].to_numpy() for c in names], axis=1)
        a, b, wa, wb = x[side == i], x[side == j], w[side == i], w[side == j]
        total = float(np.sum([wa[k : k + 256] @ _pair_sums(a[k : k + 256], b, wb) for k in range(0, len(a), 256)])) if len(a) and len(b) else 0.0
        return pa.table({"pairs": [total if i == j else 2 * total]})

    return spread.groupBy("i", "j").applyInArrow(run, "pairs double").agg(F.sum("pairs").alias("pairs"))


def discrepancy(points: DataFrame, n: int, x: str = "x") -> DataFrame:
    """(count, discrepancy_sq): the exact sum over all pairs. Rows with a null point take no part.

    Equal points count as one of their number. Up to ``TILED`` distinct points,
    or on more than ``BLOCK_DIMS`` axes, pairs of distinct points are summed
    tile by tile (``_pairs_in_tiles``), which is quadratic in their number; else
    in blocks (``_pairs_in_blocks``), n log(n) to the power of the axes' number.
    """
    known = points.where(F.col(x).isNotNull()).select(*[F.element_at(x, d + 1).cast("double").alias(f"x{d}") for d in range(n)])
    distinct = durable(known.groupBy(*known.columns).agg(F.count("*").cast("double").alias("w")))
    count, own = distinct.count(), F.col("w")
    for c in known.columns:
        own = own * F.col(c) * (1 - F.col(c))
    singles = distinct.agg(F.sum(own).alias("singles"), F.coalesce(F.sum("w"), F.lit(0.0)).cast("long").alias("count"))
    pairs = _pairs_in_blocks if count > TILED and n <= BLOCK_DIMS else _pairs_in_tiles
    return _closed_form(singles, pairs(distinct, count, n), n)


def _closed_form(singles: DataFrame, pairs: DataFrame, n: int) -> DataFrame:
    size = F.col("count").cast("double")
    value = F.col("pairs") / (size * size) - F.col("singles") * 2.0 ** (1 - n) / size + 12.0**-n
    return singles.crossJoin(pairs).select("count", value.alias("discrepancy_sq"))


def discrepancy_1d(points: DataFrame, value: str) -> DataFrame:
    """(count, discrepancy_sq) on the line from ranks: in sorted order the pair sum is linear.

    Ranks come from range counts and in-range order, so no task sorts all values.
    """
    from .latin import global_rank

    v = points.where(F.col(value).isNotNull()).select(F.col(value).cast("double").alias("v")).withColumn("one", F.lit(0)).withColumn("id", F.monotonically_increasing_id())
    ranked = global_rank(v, "one", ["v", "id"])
    sizes = v.agg(F.count("*").alias("count"))
    # a pair i before j gives v_i (1 - v_j); summed over pairs: the terms of v_i and of v_i v_j apart
    w = Window.partitionBy("range_").orderBy("v", "id").rowsBetween(Window.unboundedPreceding, -1)
    cell = ranked.withColumn("range_", F.floor(F.col("rank") / 4096))
    inside = cell.withColumn("before", F.coalesce(F.sum("v").over(w), F.lit(0.0)))
    parts = cell.groupBy("range_").agg(F.sum("v").alias("part"))
    offsets = parts.withColumn("offset", F.coalesce(F.sum("part").over(Window.orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).drop("part")
    summed = inside.join(F.broadcast(offsets), "range_").agg(
        F.sum((F.col("before") + F.col("offset")) * (1 - F.col("v"))).alias("cross"),
        F.sum(F.col("v") * (1 - F.col("v"))).alias("own"),
    )
    pairs = 2 * F.col("cross") + F.col("own")
    return summed.crossJoin(sizes).select("count", (pairs / (F.col("count") * F.col("count")) - F.col("own") / F.col("count") + 1.0 / 12).alias("discrepancy_sq"))


def boxes(spark, m: int, n: int, seed: int) -> DataFrame:
    """(box_id, lo, hi): m keyed boxes; ordered corners of two uniforms per axis."""
    a = [rng.uniform(seed, "box", F.col("id"), d, 0) for d in range(n)]
    b = [rng.uniform(seed, "box", F.col("id"), d, 1) for d in range(n)]
    low, high = [F.least(p, q) for p, q in zip(a, b)], [F.greatest(p, q) for p, q in zip(a, b)]
    return spark.range(m).select(F.col("id").alias("box_id"), F.array(*low).alias("lo"), F.array(*high).alias("hi"))


def discrepancy_boxes(points: DataFrame, n: int, m: int, seed: int = 0, x: str = "x") -> DataFrame:
    """(boxes, discrepancy_sq) estimated from m boxes: 2**-n times the mean squared gap of share and volume.

    The boxes (a parameter, not the data) go to every task; points stream by in
    Arrow batches and each task sends m counts. Rows with a null point take no
    part.
    """
    spark = points.sparkSession
    made = boxes(spark, m, n, seed).orderBy("box_id").toArrow()
    corners = spark.sparkContext.broadcast(tuple(np.array(made[side].to_pylist()).reshape(m, n) for side in ("lo", "hi")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lo, hi = corners.value
        hits, count = np.zeros(m, np.int64), 0
        for batch in batches:
            p = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
            count += len(p)
            for k in range(0, len(p), 2048):
                inside = np.ones((m, len(p[k : k + 2048])), bool)
                for d in range(n):
                    v = p[k : k + 2048, d]
                    inside &= (v >= lo[:, d, None]) & (v < hi[:, d, None])
                hits += inside.sum(axis=1)
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m)), pa.array(hits), pa.array(np.full(m, count))], names=["box_id", "hits", "count"])

    chosen = points.where(F.col(x).isNotNull()).select(F.col(x).alias("x"))
    found = chosen.mapInArrow(run, "box_id long, hits long, count long").groupBy("box_id").agg(F.sum("hits").alias("hits"), F.sum("count").alias("count"))
    volumes = spark.createDataFrame([(k, float(v)) for k, v in enumerate((corners.value[1] - corners.value[0]).prod(axis=1))], "box_id long, volume double")
    gap = F.col("hits") / F.col("count") - F.col("volume")
    return found.join(F.broadcast(volumes), "box_id").agg(F.count("*").alias("boxes"), (F.avg(gap * gap) * 2.0**-n).alias("discrepancy_sq"))
