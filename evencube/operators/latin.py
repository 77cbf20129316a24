"""Latin versions of stratified designs: bins handed out by centre order, or matched to boxes.

Along one axis a box overlaps a run of the N bins. ``cog_bins`` sorts boxes by
centre and hands out bins in order. ``match_bins`` finds a perfect matching:
keyed greedy start, then augmenting paths; axes and straddle-free components
are matched in separate tasks.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import rng
from ..plans.checkpoints import durable

#: Slack at bin edges, in bins, so that rounding never makes a box lose a bin it only touches.
EDGE = 1e-9


def long_form(strata: DataFrame) -> DataFrame:
    """(stratum_id, dim, lo, hi): one row per stratum and axis."""
    return strata.select("stratum_id", F.posexplode(F.arrays_zip("lo", "hi")).alias("dim", "side")).select("stratum_id", "dim", "side.lo", "side.hi")


#: Rows of a range that is ranked in one task.
RANGE_ROWS = 200_000


def global_rank(rows: DataFrame, by: str, order: list[str]) -> DataFrame:
    """Zero-based rank within ``by`` (a few values, such as axes) without putting a whole axis into one task.

    Rows are dealt to ranges of the whole order, ties included, whose number
    grows with the rows; ranks are counted inside a range and offset by the
    ranges before. The last of ``order`` should tell rows apart.
    """
    parts = max(1, -(-rows.count() // RANGE_ROWS))
    # written once, so that both passes see the same ranges
    placed = durable(rows.repartitionByRange(parts, by, *order).withColumn("range_", F.spark_partition_id()))
    sizes = placed.groupBy(by, "range_").agg(F.count("*").alias("size_"))
    before = sizes.withColumn("before_", F.sum("size_").over(Window.partitionBy(by).orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)))
    inside = F.row_number().over(Window.partitionBy(by, "range_").orderBy(*order)) - 1
    return (
        placed.withColumn("inside_", inside)
        .join(F.broadcast(before.select(by, "range_", F.coalesce("before_", F.lit(0)).alias("before_"))), [by, "range_"])
        .withColumn("rank", (F.col("before_") + F.col("inside_")).cast("long"))
        .drop("inside_", "before_", "range_")
    )


def bucket_rank(rows: DataFrame, by: str, order: list[str], count: int) -> DataFrame:
    """``global_rank`` for a first order column spread evenly over [0, 1]: a bucket sort, linear in the rows.

    Buckets are equal slices of the value, about ``RANGE_ROWS`` rows each where
    the spread is even; their sizes are counted, nothing is sampled or sorted
    across buckets.
    """
    buckets = max(1, -(-count // RANGE_ROWS))
    slot = F.least(F.greatest(F.floor(F.col(order[0]) * buckets), F.lit(0)), F.lit(buckets - 1)).cast("int")
    placed = rows.withColumn("slot_", slot)
    sizes = placed.groupBy(by, "slot_").agg(F.count("*").alias("size_"))
    before = sizes.withColumn("before_", F.sum("size_").over(Window.partitionBy(by).orderBy("slot_").rowsBetween(Window.unboundedPreceding, -1)))
    inside = F.row_number().over(Window.partitionBy(by, "slot_").orderBy(*order)) - 1
    found = placed.withColumn("inside_", inside).join(F.broadcast(before.select(by, "slot_", F.coalesce("before_", F.lit(0)).alias("before_"))), [by, "slot_"])
    return found.withColumn("rank", (F.col("before_") + F.col("inside_")).cast("long")).drop("inside_", "before_", "slot_")


def cog_bins(strata: DataFrame, count: int, seed: int = 0, rank: str = "range") -> DataFrame:
    """(stratum_id, dim, lo, hi, bin, violation): bins in order of box centres, ties by a keyed number.

    ``rank`` is "range", or "bucket" for the linear bucket sort of centres that
    lie evenly in the unit cube; both give the same bins.
    """
    if rank not in ("range", "bucket"):
        raise ValueError("rank is range or bucket")
    rows = long_form(strata).withColumn("centre", F.round((F.col("lo") + F.col("hi")) / 2, 12))
    rows = rows.withColumn("tie", rng.uniform(seed, "cog", F.col("stratum_id"), F.col("dim")))
    order = ["centre", "tie", "stratum_id"]
    ranked = global_rank(rows, "dim", order) if rank == "range" else bucket_rank(rows, "dim", order, count)
    return with_violation(ranked.withColumnRenamed("rank", "bin").drop("centre", "tie"), count)


def with_violation(assigned: DataFrame, count: int) -> DataFrame:
    """Flags bins that do not overlap their box."""
    low, high = F.col("bin") / F.lit(float(count)), (F.col("bin") + 1) / F.lit(float(count))
    meets = (F.least("hi", high) - F.greatest("lo", low)) > F.lit(EDGE / count)
    return assigned.withColumn("violation", ~meets)


def draw_in_bins(assigned: DataFrame, count: int, seed: int = 0, centred: bool = False) -> DataFrame:
    """(point_id, x): one point per stratum, inside box and bin; where they miss each other, inside the box."""
    low = F.greatest("lo", F.col("bin") / F.lit(float(count)))
    high = F.least("hi", (F.col("bin") + 1) / F.lit(float(count)))
    low, high = F.when(F.col("violation"), F.col("lo")).otherwise(low), F.when(F.col("violation"), F.col("hi")).otherwise(high)
    u = F.lit(0.5) if centred else rng.uniform(seed, "binned", F.col("stratum_id"), F.col("dim"))
    return widen(assigned.select("stratum_id", "dim", (low + (high - low) * u).alias("value")))


def widen(rows: DataFrame) -> DataFrame:
    """(point_id, x) from one row per stratum and axis."""
    side = F.array_sort(F.collect_list(F.struct("dim", "value")))
    return rows.groupBy(F.col("stratum_id").alias("point_id")).agg(F.transform(side, lambda s: s.value).alias("x"))


def latin_violations(points: DataFrame, count: int, n: int) -> DataFrame:
    """(dim, empty_bins): bins of width 1/count without a point, per axis."""
    rows = points.select(F.posexplode("x").alias("dim", "v"))
    bin_ = F.least(F.greatest(F.floor(F.col("v") * count), F.lit(0)), F.lit(count - 1))
    return rows.groupBy("dim").agg((F.lit(count) - F.count_distinct(bin_)).cast("long").alias("empty_bins"))


def latinize_by_rank(points: DataFrame, key: str, columns: list[str], seed: int = 0, centred: bool = True) -> DataFrame:
    """(key, dim, rank, value): every column replaced by (rank + u) / rows; ties by key."""
    pairs = F.array(*[F.struct(F.lit(d).alias("dim"), F.col(c).cast("double").alias("v")) for d, c in enumerate(columns)])
    rows = points.select(F.col(key).alias("key"), F.explode(pairs).alias("p")).select("key", "p.dim", "p.v").where("v is not null")
    ranked = global_rank(rows, "dim", ["v", "key"])
    sizes = rows.groupBy("dim").agg(F.count("*").alias("n"))
    u = F.lit(0.5) if centred else rng.uniform(seed, "rank", F.col("key"), F.col("dim"))
    return ranked.join(F.broadcast(sizes), "dim").select("key", "dim", "rank", ((F.col("rank") + u) / F.col("n")).alias("value"))


# matching


def bin_runs(lo: np.ndarray, hi: np.ndarray, count: int) -> tuple[np.ndarray, np.ndarray]:
    """First and last bin that each interval overlaps."""
    first = np.floor(lo * count + EDGE).astype(np.int64)
    last = np.ceil(hi * count - EDGE).astype(np.int64) - 1
    return np.clip(first, 0, count - 1), np.clip(np.maximum(first, last), 0, count - 1)


def sweep_matching(first: np.ndarray, last: np.ndarray, start: int = 0) -> np.ndarray:
    """Bins by earliest deadline; optimal for runs, but biased: a feasibility check and a last repair."""
    order, out, heap, k = np.argsort(first, kind="stable"), np.full(len(first), -1, np.int64), [], 0
    for bin_ in range(start, start + len(first)):
        while k < len(order) and first[order[k]] <= bin_:
            heapq.heappush(heap, (int(last[order[k]]), int(order[k])))
            k += 1
        if not heap or heap[0][0] < bin_:
            raise ValueError("no perfect matching")
        out[heapq.heappop(heap)[1]] = bin_
    return out


def augmenting_matching(first: np.ndarray, last: np.ndarray, prefer: np.ndarray, start: int = 0) -> np.ndarray:
    """A perfect matching grown from ``prefer`` (a wished bin per box, -1 for none) by shortest augmenting paths over runs."""
    n = len(first)
    bin_of, box_of = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    for box, bin_ in enumerate(prefer.tolist()):
        if bin_ >= 0 and first[box] <= bin_ <= last[box] and box_of[bin_ - start] < 0:
            bin_of[box], box_of[bin_ - start] = bin_, box
    for box in np.flatnonzero(bin_of < 0).tolist():
        # breadth first over boxes; bins seen once are skipped by pointers to the next unseen
        following = np.arange(n + 1)

        def unseen(b: int) -> int:
            while following[b] != b:
                following[b] = following[following[b]]
                b = int(following[b])
            return b

        came, queue, free = {}, [box], -1
        for at in queue:
            b = unseen(int(first[at]) - start)
            while b <= last[at] - start:
                following[b] = b + 1
                came[b] = at
                if box_of[b] < 0:
                    free = b
                    break
                queue.append(int(box_of[b]))
                b = unseen(b)
            if free >= 0:
                break
        if free < 0:
            raise ValueError("no perfect matching")
        while True:
            at = came[free]
            before = int(bin_of[at]) - start if bin_of[at] >= 0 else -1
            bin_of[at], box_of[free] = free + start, at
            if at == box:
                break
            free = before
    return bin_of


def greedy_start(first: np.ndarray, last: np.ndarray, start: int, *key: int) -> np.ndarray:
    """Boxes in keyed order each take a keyed free bin of their run."""
    n = len(first)
    free, wish = np.ones(n, bool), np.full(n, -1, np.int64)
    for box in np.argsort(rng.fast_key(*key, 21, np.arange(n)), kind="stable").tolist():
        run = np.flatnonzero(free[first[box] - start : last[box] - start + 1])
        if len(run):
            pick = int(run[int(rng.fast_uniform(*key, 22, box) * len(run))]) + int(first[box])
            wish[box] = pick
            free[pick - start] = False
    return wish


def match_axis(lo: np.ndarray, hi: np.ndarray, count: int, start: int, init: str, *key: int) -> np.ndarray:
    """Bins start.. matched to the intervals of one component."""
    first, last = bin_runs(lo, hi, count)
    if init == "sweep":
        return sweep_matching(first, last, start)
    if init == "cog":
        tie = rng.fast_key(*key, 23, np.arange(len(lo)))
        order = np.lexsort((tie, np.round((lo + hi) / 2, 12)))
        wish = np.empty(len(lo), np.int64)
        wish[order] = np.arange(len(lo)) + start
    elif init == "random_greedy":
        wish = greedy_start(first, last, start, *key)
    else:
        raise ValueError(f"unknown init {init!r}")
    return augmenting_matching(first, last, wish, start)


#: Bins of a range whose running sums one task works out.
BIN_RANGE = 4096


def components(rows: DataFrame, count: int) -> DataFrame:
    """``rows`` (dim, lo, hi, ...) with comp, the first bin of the run of bins that no box straddles out of.

    Each component has as many boxes as bins. Boxes that straddle a bin's lower
    edge are counted by running sums inside bin ranges, offset by the ranges
    before, so no task sees a whole axis.
    """
    first = F.floor(F.col("lo") * count + EDGE).cast("long")
    last = F.greatest(F.ceil(F.col("hi") * count - EDGE).cast("long") - 1, first)
    runs = rows.withColumn("first_", first).withColumn("last_", last)
    # an edge below bin b is straddled by the boxes with first < b <= last
    change = runs.select("dim", F.explode(F.array(F.struct((F.col("first_") + 1).alias("bin"), F.lit(1).alias("d")), F.struct((F.col("last_") + 1).alias("bin"), F.lit(-1).alias("d")))).alias("c"))
    grid = rows.select("dim").distinct().withColumn("bin", F.explode(F.sequence(F.lit(0), F.lit(count - 1)))).select("dim", F.col("bin").cast("long"), F.lit(0).alias("d"))
    steps = change.select("dim", "c.bin", "c.d").unionByName(grid).groupBy("dim", "bin").agg(F.sum("d").alias("d")).withColumn("range_", F.floor(F.col("bin") / BIN_RANGE))
    sums = steps.groupBy("dim", "range_").agg(F.sum("d").alias("total"))
    before = F.coalesce(F.sum("total").over(Window.partitionBy("dim").orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inside = Window.partitionBy("dim", "range_").orderBy("bin")
    straddled = steps.withColumn("s_", F.sum("d").over(inside)).join(F.broadcast(sums.select("dim", "range_", before.alias("before"))), ["dim", "range_"])
    cut = straddled.withColumn("cut", F.when(F.col("s_") + F.col("before") == 0, F.col("bin")))
    lasts = cut.groupBy("dim", "range_").agg(F.max("cut").alias("m"))
    carried = lasts.select("dim", "range_", F.max("m").over(Window.partitionBy("dim").orderBy("range_").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))
    starts = cut.withColumn("own", F.max("cut").over(inside)).join(F.broadcast(carried), ["dim", "range_"])
    starts = starts.select("dim", F.col("bin").alias("first_"), F.coalesce("own", "carried").alias("comp"))
    return runs.join(starts, ["dim", "first_"]).drop("first_", "last_")


def match_bins(strata: DataFrame, count: int, init: str = "random_greedy", seed: int = 0) -> DataFrame:
    """(stratum_id, dim, lo, hi, bin, violation): a perfect matching of boxes and bins on every axis."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("stratum_id", ignore_index=True)
        start = int(pdf["comp"].iloc[0])
        pdf["bin"] = match_axis(pdf["lo"].to_numpy(), pdf["hi"].to_numpy(), count, start, init, seed, int(pdf["dim"].iloc[0]), start)
        return pdf[["stratum_id", "dim", "lo", "hi", "bin"]]

    grouped = components(long_form(strata), count).groupBy("dim", "comp")
    return with_violation(grouped.applyInPandas(run, "stratum_id long, dim int, lo double, hi double, bin long"), count)


def latin_np(lo: np.ndarray, hi: np.ndarray, how: str, *key: int) -> np.ndarray:
    """Points of a Latin design over the strata: ``cog`` bins in centre order, else ``match_axis`` from that start (``cog_matched``: from centre order)."""
    count, n = lo.shape
    out = np.empty_like(lo)
    for d in range(n):
        if how == "cog":
            tie = rng.fast_key(*key, 24, d, np.arange(count))
            order = np.lexsort((tie, np.round((lo[:, d] + hi[:, d]) / 2, 12)))
            bins = np.empty(count, np.int64)
            bins[order] = np.arange(count)
        else:
            bins = match_axis(lo[:, d], hi[:, d], count, 0, how.removesuffix("_matched"), *key, d)
        low, high = np.maximum(lo[:, d], bins / count), np.minimum(hi[:, d], (bins + 1) / count)
        miss = high - low <= EDGE / count
        low, high = np.where(miss, lo[:, d], low), np.where(miss, hi[:, d], high)
        out[:, d] = low + (high - low) * rng.fast_uniform(*key, 25, d, np.arange(count))
    return out
