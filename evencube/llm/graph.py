"""Connected components, and joins that split hot keys.

Graphs of more edges than one task should hold are contracted by alternating
star rounds; one task joins what is within that bound.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable

#: A key is hot when it has more rows than this and than a ``HOT_KEYS``-th of them all: there are fewer than HOT_KEYS such.
HOT_ROWS, HOT_KEYS = 256, 8192

#: Edges that one task joins; more are contracted by all tasks in rounds.
EDGES = 1 << 18


def join_split(rows: DataFrame, values: DataFrame, keys: Sequence[str], n: str, total: int) -> DataFrame:
    """Inner join of ``rows`` with ``values``, which has one row a key and in column ``n`` the key's number of rows.

    The rows of hot keys stay where they are and meet a broadcast of those
    keys' values, fewer than ``HOT_KEYS`` rows whatever the size; all others
    are joined by shuffle. ``total`` is the number of rows.
    """
    keys, bound = list(keys), max(HOT_ROWS, total // HOT_KEYS)
    hot = values.where(F.col(n) > bound).drop(n)
    cold = values.where(F.col(n) <= bound).drop(n)
    there = F.broadcast(hot.select(*keys))
    return rows.join(F.broadcast(hot), keys).unionByName(rows.join(there, keys, "left_anti").join(cold, keys))


def _large_star(edges: DataFrame, total: int) -> DataFrame:
    """Every larger neighbour of a node moves to the node's smallest neighbour (or the node itself)."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("low"), F.count_if(F.col("b") > F.col("a")).alias("n"))
    up = edges.select(F.col("b").alias("a"), F.col("a").alias("b"))
    moved = join_split(up, least, ["a"], "n", total).select(F.col("b").alias("a"), F.least("a", "low").alias("b"))
    return moved.where("a <> b").distinct()


def _small_star(edges: DataFrame, total: int) -> DataFrame:
    """Every smaller neighbour of a node, and the node, move to the smallest of them; edges point down (a > b)."""
    least = edges.groupBy("a").agg(F.min("b").alias("low"), F.count("*").alias("n"))
    moved = join_split(edges, least, ["a"], "n", total).select(F.col("b").alias("a"), F.col("low").alias("b"))
    own = least.select("a", F.col("low").alias("b"))
    return moved.unionByName(own).where("a <> b").distinct()


def joined(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the smallest node that each can reach) of the edges between ``a`` and ``b``."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    low = np.arange(len(nodes))
    while True:
        least, new = np.minimum(low[x], low[y]), low.copy()
        np.minimum.at(new, low[x], least)
        np.minimum.at(new, low[y], least)
        while not np.array_equal(new[new], new):
            new = new[new]
        if np.array_equal(new, low):
            return nodes, nodes[low]
        low = new


def _in_one_task(edges: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = pa.Table.from_batches(batches, pa.schema([("a", pa.int64()), ("b", pa.int64())]))
        node, component = joined(found["a"].to_numpy(), found["b"].to_numpy())
        yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(component, pa.int64())], names=["node", "component"])

    return edges.select(F.col("a").cast("long"), F.col("b").cast("long")).repartition(1).mapInArrow(run, "node long, component long")


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of an undirected edge; component is the smallest node that can be reached.

    Loops and repeated edges do no harm; edges with a null end are left out.
    Nothing is collected. Up to ``EDGES`` edges are joined in one task; beyond,
    no hub's edges are gathered, and the number of rounds grows with the
    logarithm of the graph.
    """
    pairs = edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
    now = durable(pairs.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")))
    if now.count() <= EDGES:
        return durable(_in_one_task(now))
    now = durable(now.distinct())
    mark = _mark(now)
    while mark[0] > EDGES:
        now = durable(_small_star(durable(_large_star(now, mark[0])), mark[0]))
        before, mark = mark, _mark(now)
        if mark == before:
            break
    if mark[0] <= EDGES:
        return durable(_in_one_task(now))
    stars = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return stars.unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def _mark(edges: DataFrame) -> tuple[int, int]:
    """Number and order-free checksum of the edges."""
    found = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
    return found.n, int(found.h or 0)
