"""Near duplicates by tensored MinHash banding, confirmed on full shingle sets.

Two collections of ``m`` half keys, each of ``HASHES`` minhashes, stand for all
``m * m`` tables whose keys pair a half key of one collection with one of the
other: the tables of twice as long keys cost only the square root of their
minhashes. Documents of equal sets form one class. A table bucket's smallest
class is its hub. Every class is first compared, by whole sets, with two of its
hubs; what that joins is contracted, and only in buckets that still hold several
components are the other pairs compared too: one by one those of small buckets,
tile by tile those of blocks of large ones. They must agree in enough half keys
before sets are sent. Components of the links are the result.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bytescan
from .common import durable, map_text, small_side
from .graph import components, join_split

#: Minhashes of a half key; chance that a pair at the threshold shares no table.
HASHES, MISS = 4, 2e-4

#: Chance that a pair at the threshold agrees in too few half keys to be compared.
FEW = 2e-5

#: Classes of a bucket whose pairs are made by a join; larger ones are compared tile by tile, a side of TILE each.
SMALL, TILE = 16, 256

#: Shingles that a tile's product takes at once.
COLUMNS = 1 << 14

#: Members that one hub meets in one task.
HUB_ROWS = 128

SEED = 0x5EED_0F_5E75


def half_keys(similarity: float, hashes: int = HASHES, miss: float = MISS) -> int:
    """Half keys a collection needs so that a pair at ``similarity`` is missed with chance ``miss`` at most."""
    return max(1, math.ceil(math.log(miss / 2) / math.log(1 - similarity**hashes))) if similarity < 1 else 1


def least_agreement(similarity: float, m: int, hashes: int = HASHES, few: float = FEW) -> int:
    """Half keys that two sets at ``similarity`` agree in, at least, but for a chance of ``few``; of 2 m."""
    p, below, k = similarity**hashes, 0.0, 0
    while k < 2 * m and (below := below + math.comb(2 * m, k) * p**k * (1 - p) ** (2 * m - k)) <= few:
        k += 1
    return max(k, 2)


def sketcher(words: int, m: int) -> Callable[[pa.Array], list[pa.Array]]:
    """Per text: set size, two 64-bit set signatures, m half keys of either collection (none for an empty set)."""
    rng = np.random.default_rng(SEED)
    odd = rng.integers(0, 1 << 63, 2 * m * HASHES, np.uint64) * np.uint64(2) + np.uint64(1)
    salt = rng.integers(0, 1 << 63, 2 * m * HASHES, np.uint64)

    def work(text: pa.Array) -> list[pa.Array]:
        sizes, first, second, halves = [], [], [], []
        for part in bytescan.slices(text):
            row, h = bytescan.shingles(bytescan.scan(part, bytescan.NON_SPACE), words)
            n = np.bincount(row, minlength=len(part))
            full = np.flatnonzero(n)
            at = (np.cumsum(n) - n)[full]
            keys = np.zeros((len(part), 2 * m), np.uint64)
            s1, s2 = np.zeros(len(part), np.uint64), np.zeros(len(part), np.uint64)
            if len(full):
                with np.errstate(over="ignore"):
                    s1[full] = np.add.reduceat(h, at, dtype=np.uint64)
                    s2[full] = np.add.reduceat(bytescan.mix(h ^ np.uint64(SEED)), at, dtype=np.uint64)
                    for k in range(2 * m):
                        key = np.full(len(full), np.uint64(k + 1))
                        for i in range(k * HASHES, (k + 1) * HASHES):
                            key = bytescan.mix(key * np.uint64(0xD6E8FEB86659FD93) + np.minimum.reduceat((h ^ salt[i]) * odd[i], at))
                        keys[full, k] = key
            sizes.append(n)
            first.append(s1)
            second.append(s2)
            halves.append(keys)
        joined = lambda xs, kind: np.concatenate(xs) if xs else np.empty(0, kind)
        n, keys = joined(sizes, np.int64), joined(halves, np.uint64).reshape(-1, 2 * m).view(np.int64)
        kept = keys[n > 0]
        ends = pa.array(np.r_[0, np.cumsum(np.where(n > 0, m, 0))], pa.int32())
        lists = [pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(side).ravel(), pa.int64())) for side in (kept[:, :m], kept[:, m:])]
        return [pa.array(n.astype(np.int64)), *(pa.array(joined(s, np.uint64).view(np.int64)) for s in (first, second)), *lists]

    return work


def set_bytes(words: int) -> Callable[[pa.Array], list[pa.Array]]:
    """Per text: its distinct shingle hashes as bytes."""

    def work(text: pa.Array) -> list[pa.Array]:
        out: list[bytes] = []
        for part in bytescan.slices(text):
            row, h = bytescan.shingles(bytescan.scan(part, bytescan.NON_SPACE), words)
            at = np.searchsorted(row, np.arange(len(part) + 1)).tolist()
            out += [h[a:b].tobytes() for a, b in zip(at[:-1], at[1:])]
        return [pa.array(out, pa.binary())]

    return work


def shared_with(hub: np.ndarray, sets: list[np.ndarray]) -> np.ndarray:
    """How many values of each of ``sets`` are in the sorted ``hub``."""
    every = np.concatenate(sets)
    at = np.minimum(np.searchsorted(hub, every), len(hub) - 1)
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    return np.bincount(owner[hub[at] == every], minlength=len(sets))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every document.

    A document's set holds its distinct shingles of ``words`` words (A-Z
    lower-cased, split at white space); fewer words make one shingle; a null or
    wordless text has an empty set and is linked with nothing. Documents are
    linked when ``percent`` % of their union is shared, confirmed on whole sets
    (64-bit shingle hashes). component_id is the smallest id that links reach,
    kept says that it is the document's own. Repeated rows come back repeated;
    rows that share an id count as connected; a null id keeps its row, with a
    null component and kept false. A pair at the threshold shares no table, or
    too few half keys, with chance ``MISS + FEW`` at most, one of higher
    similarity still less.
    """
    if not 0 < percent <= 100:
        raise ValueError("0 < percent <= 100")
    m = half_keys(percent / 100)
    source = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    halves = T.ArrayType(T.LongType())
    fields = [*(T.StructField(n, T.LongType()) for n in ("n_shingles", "s1", "s2")), T.StructField("left", halves), T.StructField("right", halves)]
    sketched = durable(map_text(source, "text", fields, lambda: sketcher(words, m)).drop("text"))
    known = sketched.where("doc_id is not null and n_shingles > 0")
    # one row per class of equal sets
    kept = [F.first(c).alias(c) for c in ("left", "right", "n_shingles")]
    classes = durable(known.groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n"), *kept))
    repeated = durable(known.groupBy("doc_id").count().where("count > 1").select("doc_id"))
    repeats = repeated.count() > 0

    paired = durable(_table_keys(classes, m))
    total = paired.count()
    hubs = durable(paired.groupBy("key").agg(F.min("rep").alias("b"), F.count("*").alias("n")).where("n > 1"))
    stars = durable(join_split(paired, hubs, ["key"], "n", total).where("rep <> b").groupBy(F.col("rep").alias("a"), "b").agg(F.count("*").alias("tables")))
    reps = stars.select(F.col("a").alias("doc_id")).unionByName(stars.select(F.col("b").alias("doc_id"))).distinct()
    sets = durable(_sets(source, small_side(durable(reps)), repeated if repeats else None, words))

    # the smallest hub joins a family to one star, the one met most often reaches over its drift
    two = stars.groupBy("a").agg(F.min("b").alias("x"), F.max_by("b", F.struct("tables", -F.col("b"))).alias("y"))
    first = durable(two.select("a", F.explode(F.array_distinct(F.array("x", "y"))).alias("b")))
    links = _confirmed(first, sets, percent)
    if repeats:
        links = links.unionByName(_of_one_id(known, repeated, classes))
    joined = components(links)
    members = _open_buckets(paired, total, hubs, stars, joined)
    sketch = classes.select("rep", "left", "right", "n_shingles")
    least = least_agreement(percent / 100, m)
    more = _confirmed(_small_pairs(members, sketch, first, least, percent), sets, percent)
    more = durable(more.unionByName(_tile_links(members, sketch, sets, least, percent)))
    if more.count():
        joined = components(joined.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more))

    linked = small_side(joined.select(F.col("node").alias("rep"), "component"))
    of_class = classes.select("s1", "s2", "rep", "n").join(linked, "rep", "left")
    of_class = of_class.select("s1", "s2", "n", F.coalesce("component", "rep").alias("component_id"))
    found = join_split(known.select("doc_id", "n_shingles", "s1", "s2"), of_class, ["s1", "s2"], "n", sketched.count())
    kept = (F.col("doc_id") == F.col("component_id")).alias("kept")
    alone = sketched.where("doc_id is null or n_shingles = 0")
    own = F.when(F.col("n_shingles") == 0, F.col("doc_id")).alias("component_id")
    return found.select("doc_id", "n_shingles", "component_id", kept).unionByName(
        alone.select("doc_id", "n_shingles", own, F.col("doc_id").isNotNull().alias("kept"))
    )


def _table_keys(classes: DataFrame, m: int) -> DataFrame:
    """(rep, key) of every table that a class may share.

    A table's key can only be shared where both its half keys are, so half keys
    of a single class are dropped before they are paired.
    """
    total = classes.count() * m

    def shared(side: str) -> DataFrame:
        rows = classes.select("rep", F.xxhash64("s1", "s2").alias("class"), F.explode(side).alias(side))
        met = rows.groupBy(side).agg(F.count("*").alias("n")).where("n > 1")
        return join_split(rows, met, [side], "n", total)

    return shared("left").join(shared("right"), ["rep", "class"]).select("rep", F.xxhash64("left", "right").alias("key"))


def _sets(source: DataFrame, reps: DataFrame, repeated: DataFrame | None, words: int) -> DataFrame:
    """(rep, size, set) of the classes named by ``reps``; an id of several texts has several, one of repeated rows one."""
    texts = source.join(reps, "doc_id", "left_semi")
    if repeated is not None:
        many = texts.join(repeated, "doc_id", "left_semi").withColumns({"__h": F.xxhash64("text"), "__g": F.xxhash64(F.lit(1), "text")})
        texts = texts.join(repeated, "doc_id", "left_anti").unionByName(many.dropDuplicates(["doc_id", "__h", "__g"]).drop("__h", "__g"))
    found = map_text(texts, "text", [T.StructField("set", T.BinaryType())], lambda: set_bytes(words))
    return found.select(F.col("doc_id").alias("rep"), (F.octet_length("set") / 8).cast("long").alias("size"), "set").where("size > 0")


def _of_one_id(known: DataFrame, repeated: DataFrame, classes: DataFrame) -> DataFrame:
    """(a, b): every id of repeated rows with the classes of its texts."""
    rows = known.select("doc_id", "s1", "s2").join(repeated, "doc_id", "left_semi").distinct()
    return rows.join(classes.select("s1", "s2", "rep"), ["s1", "s2"]).where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))


def _open_buckets(paired: DataFrame, total: int, hubs: DataFrame, stars: DataFrame, joined: DataFrame) -> DataFrame:
    """(key, rep, c, size) of the buckets that hold several components c so far."""
    labels = small_side(joined)
    one, two = labels.toDF("a", "c"), labels.toDF("b", "d")
    apart = stars.join(one, "a", "left").join(two, "b", "left").where(F.coalesce("c", "a") != F.coalesce("d", "b"))
    left = hubs.join(apart.select("b").distinct(), "b", "left_semi").select("key", "n", F.col("n").alias("size"))
    members = join_split(paired, left, ["key"], "n", total).join(labels.toDF("rep", "component"), "rep", "left")
    members = durable(members.select("key", "rep", F.coalesce("component", "rep").alias("c"), "size"))
    several = members.groupBy("key").agg(F.min("c").alias("low"), F.max("c").alias("high"), F.count("*").alias("n")).where("low <> high")
    return durable(join_split(members, several.select("key", "n"), ["key"], "n", total))


def _small_pairs(members: DataFrame, sketch: DataFrame, done: DataFrame, least: int, percent: int) -> DataFrame:
    """(a, b), a > b, not in ``done``: pairs of a small bucket, of different components, that agree in enough half keys."""
    few = members.where(F.col("size") <= SMALL).select("key", "rep", "c")
    met = few.toDF("key", "a", "c").join(few.toDF("key", "b", "d"), "key").where("a > b and c <> d").select("a", "b").distinct()
    met = met.join(small_side(done), ["a", "b"], "left_anti")
    one, two = (sketch.toDF(*[f"{c}_{x}" for c in sketch.columns]).withColumnRenamed(f"rep_{x}", x) for x in "ab")
    agree = F.size(F.array_intersect("left_a", "left_b")) + F.size(F.array_intersect("right_a", "right_b"))
    like = 100 * F.least("n_shingles_a", "n_shingles_b") >= percent * F.greatest("n_shingles_a", "n_shingles_b")
    return durable(met.join(one, "a").join(two, "b").where(like & (agree >= least)).select("a", "b").distinct())


def _tile_links(members: DataFrame, sketch: DataFrame, sets: DataFrame, least: int, percent: int) -> DataFrame:
    """(a, b) links inside blocks of large buckets, from whole sets: a spanning forest of each tile.

    Buckets that share classes make a block, so that a pair is compared once.
    Sets are sent only to the tiles where a class agrees with one of another
    component in enough half keys.
    """
    large = members.where(F.col("size") > SMALL)
    low = large.groupBy("key").agg(F.min("rep").alias("b"), F.count("*").alias("n"))
    edges = join_split(large.select("key", "rep"), low, ["key"], "n", large.count()).select(F.col("rep").alias("a"), "b").distinct()
    blocks = components(edges).select(F.col("node").alias("rep"), F.col("component").alias("block"))
    parts = blocks.groupBy("block").agg(F.ceil(F.count("*") / TILE).cast("int").alias("parts"), F.count("*").alias("n"))
    placed = join_split(blocks, parts, ["block"], "n", blocks.count()).withColumn("part", F.pmod(F.xxhash64("rep"), "parts").cast("int"))
    placed = placed.join(large.select("rep", "c").distinct(), "rep").join(sketch.drop("n_shingles"), "rep")
    # part p meets every part: tile (min, max)
    tiled = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select(
        "block", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "rep", "c", F.concat("left", "right").alias("halves")
    )

    def sift(tile: pa.Table) -> pa.Table:
        c, part = tile["c"].to_numpy(), tile["part"].to_numpy()
        halves = tile["halves"].combine_chunks().flatten().to_numpy().reshape(len(c), -1)
        x, y = np.flatnonzero(part == tile["i"][0].as_py()), np.flatnonzero(part == tile["j"][0].as_py())
        same = np.zeros((len(x), len(y)), np.int16)
        for k in range(halves.shape[1]):
            same += halves[x, k][:, None] == halves[y, k][None, :]
        near = (same >= least) & (c[x][:, None] != c[y][None, :])
        return tile.drop_columns(["halves"]).take(pa.array(np.union1d(x[near.any(axis=1)], y[near.any(axis=0)]), pa.int64()))

    schema = "block long, i int, j int, part int, rep long, c long"
    asked = tiled.groupBy("block", "i", "j").applyInArrow(sift, schema).join(sets, "rep")

    def compare(tile: pa.Table) -> pa.Table:
        part, found = tile["part"].to_numpy(), [np.frombuffer(b, np.uint64) for b in tile["set"].to_pylist()]
        i, j = tile["i"][0].as_py(), tile["j"][0].as_py()
        links = forest(tile["rep"].to_numpy(), found, np.flatnonzero(part == i), np.flatnonzero(part == j), percent)
        return pa.table({"a": pa.array([a for a, _ in links], pa.int64()), "b": pa.array([b for _, b in links], pa.int64())})

    return asked.groupBy("block", "i", "j").applyInArrow(compare, "a long, b long")


def forest(ids: np.ndarray, sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links that join all of ``left`` and ``right`` (places) whose sets are similar enough: a spanning forest of them."""
    size = np.array([len(s) for s in sets])
    owner = np.repeat(np.arange(len(sets)), size)
    _, at, held = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = held > 1
    column, use = (np.cumsum(shared) - 1)[at], shared[at]
    column, owner = column[use], owner[use]
    both = np.zeros((len(left), len(right)))
    for first in range(0, int(shared.sum()), COLUMNS):
        here = (column >= first) & (column < first + COLUMNS)
        matrix = np.zeros((len(sets), min(COLUMNS, int(shared.sum()) - first)), np.float32)
        matrix[owner[here], column[here] - first] = 1
        both += matrix[left] @ matrix[right].T
    count = both.astype(np.int64)
    x, y = np.nonzero(100 * count >= percent * (size[left][:, None] + size[right][None, :] - count))
    root = list(range(len(sets)))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    out = []
    for i, j in zip(left[x].tolist(), right[y].tolist()):
        a, b = find(i), find(j)
        if a != b:
            root[max(a, b)] = min(a, b)
            out.append((int(ids[i]), int(ids[j])))
    return out


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b) of ``pairs`` whose whole sets are similar enough; ``b`` is the hub that its members are sent to.

    A hub of many members is sent to several tasks; a task holds the hub's sets
    and a batch of members.
    """
    hubs = pairs.groupBy("b").agg(F.count("*").alias("n")).withColumn("chunks", F.ceil(F.col("n") / HUB_ROWS).cast("int"))
    members = join_split(pairs, hubs, ["b"], "n", pairs.count())
    asked = members.select(F.col("a").alias("rep"), "b", F.pmod(F.xxhash64("a"), "chunks").cast("int").alias("chunk"), "a")
    own = hubs.select(F.col("b").alias("rep"), "b", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(None).cast("long").alias("a"))
    rows = asked.unionByName(own).join(sets, "rep").select("b", "chunk", "a", "set")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hub, hub_sets = (None, None), []
        for batch in batches:
            b, chunk, a = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()
            sets = [np.frombuffer(x, np.uint64) for x in batch.column(3).to_pylist()]
            out_a, out_b, k = [], [], 0
            while k < len(a):
                if a[k] is None:
                    # the hub's own rows come first
                    hub, hub_sets = ((b[k], chunk[k]), [*hub_sets, sets[k]]) if hub == (b[k], chunk[k]) else ((b[k], chunk[k]), [sets[k]])
                    k += 1
                    continue
                stop = k + 1
                while stop < len(a) and a[stop] is not None:
                    stop += 1
                size = np.array([len(s) for s in sets[k:stop]])
                near = np.zeros(stop - k, bool)
                for mine in hub_sets:
                    both = shared_with(mine, sets[k:stop])
                    near |= 100 * both >= percent * (size + len(mine) - both)
                out_a += [x for x, yes in zip(a[k:stop], near.tolist()) if yes]
                out_b += [hub[0]] * int(near.sum())
                k = stop
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], names=["a", "b"])

    dealt = rows.repartition("b", "chunk").sortWithinPartitions("b", "chunk", F.col("a").asc_nulls_first())
    return dealt.mapInArrow(run, "a long, b long")
