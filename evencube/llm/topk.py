"""Exact top-k inner products by norm-bucketed retrieval.

Candidates are dealt to groups of similar length, longest first, queries to
blocks. Groups are met in rounds, each of eight times as many as the one before:
a query's k-th best score so far, divided by its own length, is the least length
that can still matter, and only the groups that reach it are sent to it. In a
group, candidates are cut into buckets of similar length; the k-th best score
divided by the query's length and the bucket's is the bucket's local cosine
threshold: above 1 nothing later can score enough and the query is done; a high
one lets the query's strongest coordinates prune candidates; otherwise only
candidates too short are left out. What remains is verified with full products.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import durable

SCALE = 64.0

#: Candidates of a group and queries of a block; together they bound a task.
GROUP_ROWS, BLOCK_ROWS = 32_768, 4_096

#: Most ranges of lengths (of groups) and of reaches (of blocks); rows of a range beyond a group's are dealt by hash.
RANGES = 4_096

#: Groups of a round over those of the round before.
GROWTH = 8

#: Most rows of a bucket, and the shortest length in it over the longest.
BUCKET_ROWS, BUCKET_RATIO = 4_096, 0.9

#: From this local cosine threshold on, coordinates prune; how many of a query's.
COORDINATE_FROM, COORDINATES = 0.85, 3

#: Below these products of lengths, sums of float64 and of 64-bit integers are exact.
FLOAT_EXACT, LONG_EXACT = 2.0**53, 2.0**62

_NONE = np.iinfo(np.int64).min


def scaled_vectors(rows: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """(vec_id, dims, length, vector): components times 64, rounded down, as little-endian doubles, which hold them exactly.

    Rows with a null id, a null or empty vector, or a null or non-finite
    component are left out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            sizes = np.diff(lists.offsets.to_numpy())
            flat = lists.flatten()  # null lists hold nothing here
            value = flat.to_numpy(zero_copy_only=False).astype(np.float64)
            bad = ~np.isfinite(value)
            missing = lists.is_null().to_numpy(zero_copy_only=False)
            sizes = np.where(missing, 0, sizes)
            row = np.repeat(np.arange(len(sizes)), sizes)
            good = (np.bincount(row[bad], minlength=len(sizes)) == 0) & (sizes > 0) & ~batch.column(0).is_null().to_numpy(zero_copy_only=False)
            with np.errstate(over="ignore"):
                whole = np.clip(np.floor(SCALE * np.where(bad, 0, value)), -np.finfo(float).max, np.finfo(float).max).astype("<f8")
                length = np.sqrt(np.bincount(row, whole**2, len(sizes)))
            at = np.r_[0, np.cumsum(sizes)]
            kept = np.flatnonzero(good)
            vectors = [whole[at[r] : at[r + 1]].tobytes() for r in kept.tolist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(kept, pa.int64())), pa.array(sizes[kept], pa.int32()), pa.array(length[kept].astype(float)), pa.array(vectors, pa.binary())],
                names=["vec_id", "dims", "length", "vector"],
            )

    source = rows.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(embedding).alias("embedding"))
    return source.mapInArrow(run, "vec_id long, dims int, length double, vector binary")


def _matrix(table: pa.Table, dims: int) -> np.ndarray:
    return np.frombuffer(b"".join(table["vector"].to_pylist()), "<f8").reshape(-1, dims)


def products(a: np.ndarray, b: np.ndarray, longest: float) -> np.ndarray:
    """Exact integer products of the rows of ``a`` and ``b``, whose lengths multiply to ``longest`` at most; beyond 64 bits the nearest long."""
    if longest < FLOAT_EXACT:
        return (a @ b.T).astype(np.int64)
    if longest < LONG_EXACT:
        return a.astype(np.int64) @ b.astype(np.int64).T
    most, right = (1 << 63) - 1, [[int(x) for x in row] for row in b.tolist()]
    out = np.empty((len(a), len(b)), np.int64)
    for i, row in enumerate(a.tolist()):
        whole = [int(x) for x in row]
        out[i] = [max(-most, min(most, sum(map(int.__mul__, whole, other)))) for other in right]
    return out


class _Best:
    """The k best (score, id) of every query so far; ``floor`` are scores that nothing below can matter."""

    def __init__(self, queries: int, k: int, floor: np.ndarray) -> None:
        self.k, self.floor = k, floor
        self.score = np.full((queries, k), _NONE)
        self.id = np.full((queries, k), np.iinfo(np.int64).max)

    @property
    def least(self) -> np.ndarray:
        return np.maximum(self.score[:, -1], self.floor)

    def add(self, query: np.ndarray, ids: np.ndarray, score: np.ndarray) -> None:
        """Merge candidates in; ties go to smaller ids."""
        if not len(query):
            return
        met = np.unique(query)
        query = np.r_[query, np.repeat(met, self.k)]
        ids, score = np.r_[ids, self.id[met].ravel()], np.r_[score, self.score[met].ravel()]
        order = np.lexsort((ids, ~score, query))
        query, ids, score = query[order], ids[order], score[order]
        first = np.searchsorted(query, met)
        take = first[:, None] + np.arange(self.k)
        self.score[met], self.id[met] = score[take], ids[take]


def _coordinates_allow(q: np.ndarray, q_length: float, unit: np.ndarray, threshold: float) -> np.ndarray:
    """Rows of ``unit`` whose strongest query coordinates leave a cosine of ``threshold`` possible."""
    q = q / q_length
    focus = np.argsort(-np.abs(q))[:COORDINATES]
    slack = 1e-9  # rounding must never prune
    allowed = np.ones(len(unit), bool)
    for f in focus.tolist():
        middle = threshold * q[f]
        reach = np.sqrt(max(0.0, (1 - threshold**2) * (1 - q[f] ** 2))) + slack
        # a vector on the query's own side beyond the cone's edge may still lie inside it
        low = -np.inf if -q[f] >= threshold else middle - reach
        high = np.inf if q[f] >= threshold else middle + reach
        allowed &= (unit[:, f] >= low) & (unit[:, f] <= high)
    return allowed


def search_group(queries: np.ndarray, query_ids: np.ndarray, candidates: np.ndarray, ids: np.ndarray, k: int, floor: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query row, id, score) of the k best candidates of every query that score ``floor`` at least; a query's own id never counts."""
    with np.errstate(over="ignore"):
        length = np.sqrt((candidates**2).sum(axis=1))
        q_length = np.sqrt((queries**2).sum(axis=1))
    order = np.lexsort((ids, -length))
    candidates, ids, length = candidates[order], ids[order], length[order]
    best = _Best(len(queries), k, np.full(len(queries), _NONE) if floor is None else floor)
    start = 0
    while start < len(ids):
        stop = min(start + BUCKET_ROWS, len(ids))
        stop = start + max(1, int(np.searchsorted(-length[start:stop], -BUCKET_RATIO * length[start], "right")))
        longest, part, part_ids = length[start], candidates[start:stop], ids[start:stop]
        least = best.least
        score_of = np.where(least == _NONE, -np.inf, least.astype(float))
        with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
            reach = q_length * longest
            cosine = np.where(reach > 0, score_of / reach, -np.inf)
        # lengths of zero, or beyond what a double holds, are judged by the product
        plain = (reach > 0) & np.isfinite(reach)
        live = np.where(plain, cosine <= 1 + 1e-9, (reach != 0) | (score_of <= 0))
        sharp = np.flatnonzero(live & plain & (cosine >= COORDINATE_FROM))
        if len(sharp):
            unit = part / np.maximum(length[start:stop, None], 1e-300)
            for r in sharp.tolist():
                near = np.flatnonzero(_coordinates_allow(queries[r], q_length[r], unit, min(1.0, cosine[r])))
                score = products(part[near], queries[r : r + 1], reach[r])[:, 0]
                good = (score >= least[r]) & (part_ids[near] != query_ids[r])
                best.add(np.full(good.sum(), r), part_ids[near][good], score[good])
        blunt = live & ~(plain & (cosine >= COORDINATE_FROM))
        exact = reach < FLOAT_EXACT
        for rows in [x[b : b + 512] for x in (np.flatnonzero(blunt & exact), np.flatnonzero(blunt & ~exact)) for b in range(0, len(x), 512)]:
            # by length: candidates shorter than any of these queries can use
            with np.errstate(divide="ignore", invalid="ignore"):
                need = np.where(plain[rows], score_of[rows] / q_length[rows], -np.inf).min()
            long_enough = int(np.searchsorted(-length[start:stop], -need + 1e-9 * abs(need), "right")) if np.isfinite(need) else stop - start
            score = products(queries[rows], part[:long_enough], reach[rows].max())
            good = score >= least[rows][:, None]
            good &= part_ids[None, :long_enough] != query_ids[rows][:, None]
            if long_enough > 4 * k:
                # keep those from the k-th best score on
                masked = np.where(good, score, _NONE)
                good &= score >= np.partition(masked, long_enough - k, axis=1)[:, long_enough - k][:, None]
            x, y = np.nonzero(good)
            best.add(rows[x], part_ids[y], score[x, y])
        start = stop
    x, y = np.nonzero(best.score != _NONE)
    return x, best.id[x, y], best.score[x, y]


def _ranges(rows: DataFrame, value: str, most: int) -> tuple[list[float], np.ndarray, np.ndarray, np.ndarray]:
    """(bounds, first part of each range, its number of parts, its highest value) of ranges of ``value``, highest first.

    A part has ``most`` rows or so: ranges of more, as of many equal values, are
    cut into several. At most ``RANGES`` ranges come to the driver.
    """
    n = rows.count()
    wanted = min(RANGES, -(-n // most))
    bounds: list[float] = []
    if wanted > 1:
        shares = F.array(*[F.lit(k / wanted) for k in range(1, wanted)])
        found = rows.agg(F.percentile_approx(value, shares, 10 * max(1_000, wanted)).alias("q")).first().q
        bounds = sorted(set(found or []))
    alone = np.arange(len(bounds) + 1), np.ones(len(bounds) + 1, int)
    sizes = _placed(rows.select(value), value, (bounds, *alone, None), "r", F.lit(0).cast("long")).groupBy("r").agg(F.count("*").alias("n"), F.max(value).alias("high")).collect()
    by = {r.r: r for r in sizes}
    parts = np.array([max(1, -(-by[r].n // most)) if r in by else 0 for r in range(len(bounds) + 1)])
    high = np.array([by[r].high if r in by else -np.inf for r in range(len(bounds) + 1)])
    return bounds, np.cumsum(parts) - parts, parts, high


def _placed(rows: DataFrame, value: str, ranges: tuple, name: str, salt: Column) -> DataFrame:
    """``rows`` with the part of their range that each is dealt to."""
    bounds, first, parts, _ = ranges

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges = np.array(bounds, float)
        for batch in batches:
            r = len(edges) - np.searchsorted(edges, batch.column("__v").to_numpy(zero_copy_only=False), "left")
            part = first[r] + batch.column("__salt").to_numpy(zero_copy_only=False).view(np.uint64) % np.maximum(parts[r], 1).astype(np.uint64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-2], pa.array(part.astype(np.int32))], names=[*batch.schema.names[:-2], name])

    schema = T.StructType([*rows.schema.fields, T.StructField(name, T.IntegerType())])
    return rows.withColumns({"__v": F.col(value), "__salt": salt}).mapInArrow(run, schema)


def top_products(vectors: DataFrame, is_query: Column, k: int = 20) -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of every query, ties to smaller vec_id.

    ``vectors`` as ``scaled_vectors`` gives them; ``is_query`` is a condition on
    vec_id. Candidates of a query are all rows of other ids and equal
    dimension; repeated candidate rows count each, equal query rows once. Fewer
    than k candidates give all. Products are exact; one beyond 64 bits is given
    as the nearest long. Nothing is gathered in one place: groups and blocks
    are dealt by row, whatever ids, lengths or vectors repeat.
    """
    key = ["query_id", "sign"]
    ranges = _ranges(vectors, "length", GROUP_ROWS)
    groups = int(ranges[2].sum())
    reach = np.repeat(ranges[3], ranges[2])
    # written once: every round reads its own groups of it
    right = durable(_placed(vectors, "length", ranges, "group", F.xxhash64("vec_id", F.monotonically_increasing_id())))
    asked = vectors.where(is_query).withColumnRenamed("vec_id", "query_id").withColumn("sign", F.xxhash64("dims", "vector"))
    asked = asked.dropDuplicates(key)
    best, start, width = None, 0, 1
    while best is None or start < groups:
        stop = min(groups, start + width)
        if best is None:
            now = asked.withColumns({"floor": F.lit(None).cast("long"), "need": F.lit(float("-inf"))})
        else:
            least = best.where(F.col("rank") == k).select(*key, F.col("score").alias("floor"))
            # nothing shorter can score as much; a length of zero scores zero
            need = F.when(F.col("length") > 0, F.try_divide(F.col("floor").cast("double"), "length") * (1 - 1e-9)).when(F.col("floor") > 0, F.lit(float("inf")))
            now = asked.join(least, key, "left").withColumn("need", F.coalesce(F.when(F.col("floor") > 0, need), F.lit(float("-inf"))))
            now = now.where(F.col("need") <= float(reach[start]))
        found = _round(now, right, reach, start, stop, k)
        every = found if best is None else best.drop("rank").unionByName(found)
        order = Window.partitionBy(*key).orderBy(F.desc("score"), "vec_id")
        best = durable(every.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k))
        start, width = stop, width * GROWTH
    return best.select("query_id", "rank", "vec_id", "score")


def _round(asked: DataFrame, right: DataFrame, reach: np.ndarray, start: int, stop: int, k: int) -> DataFrame:
    """(query_id, sign, vec_id, score): the best of the groups ``start`` to ``stop`` - 1 for queries that need them."""
    # blocks of like need: high needs meet few groups
    bounds, first, parts, _ = ranges = _ranges(asked, "need", BLOCK_ROWS)
    blocks = int(parts.sum())
    lowest = np.repeat([*reversed(bounds), -np.inf], parts)
    here = reach[start:stop]
    # groups come longest first, so a need is met by the first so many; blocks come highest need first
    wanted = np.searchsorted(-here, -lowest, "right").tolist()
    first_block = np.searchsorted(wanted, np.arange(len(here)), "right").tolist()
    placed = _placed(asked, "need", ranges, "block", F.xxhash64("query_id", "sign"))

    def deal(name: str, other: str, steps: list[int], upto: bool) -> Column:
        """Numbers of all partners of a row's group or block."""
        each = F.array(*[F.lit(x) for x in steps] or [F.lit(0)])
        at = F.get(each, F.col(name) - (start if name == "group" else 0))
        low, high = (F.lit(0), at) if upto else (at, F.lit(blocks))
        return F.explode(F.when(low < high, F.sequence(low, high - 1))).alias(other)

    left = placed.select("query_id", "sign", "dims", "vector", "floor", "block", deal("block", "near", wanted, True))
    left = left.withColumn("group", F.col("near") + start).drop("near")
    rows = right.where(F.col("group").between(start, stop - 1))
    rows = rows.select("vec_id", "dims", "vector", "group", deal("group", "block", first_block, False))
    schema = "query_id long, sign long, vec_id long, score long"
    names = ["query_id", "sign", "vec_id", "score"]

    def run(queries: pa.Table, rows: pa.Table) -> pa.Table:
        out = [pa.table([pa.array([], pa.int64())] * 4, names=names)]
        for dims in np.unique(queries["dims"].to_numpy()).tolist():
            q, c = (t.filter(pc.equal(t["dims"], dims)) for t in (queries, rows))
            if c.num_rows:
                floor = pc.fill_null(q["floor"], _NONE).to_numpy()
                x, ids, score = search_group(_matrix(q, dims), q["query_id"].to_numpy(), _matrix(c, dims), c["vec_id"].to_numpy(), k, floor)
                row = pa.array(x, pa.int64())
                out.append(pa.table([q["query_id"].take(row), q["sign"].take(row), pa.array(ids), pa.array(score)], names=names))
        return pa.concat_tables(out)

    return left.groupBy("group", "block").cogroup(rows.groupBy("group", "block")).applyInArrow(run, schema)
