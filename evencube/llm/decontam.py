"""Benchmark decontamination: Wu-Manber multi-pattern search over words.

Every run of ``window`` words of a benchmark item is a pattern (an item of
fewer words is one pattern by itself). Patterns of one length share a shift
table over word pairs: a pair that no pattern holds lets the search jump on by
almost a whole window. Where the shift is zero, the bucket of that last pair
picks the test strings, their first pair sifts them, and the words themselves
are compared before an occurrence counts.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bytescan
from .common import map_text

WINDOW = 10

#: Most bytes of item text in one broadcast pattern table, which takes about ten times that; more items make more tables, each its own pass.
BLOCK_BYTES = 16 << 20

#: Occurrences whose bytes are compared at once.
COMPARED = 1 << 14

#: Window ends of a row that one search pointer walks over.
LANE = 256

SPAN = T.StructType([T.StructField("first", T.LongType()), T.StructField("last", T.LongType())])


@dataclass
class ItemWords:
    """The words of all items, one after another: hash and place in ``data``."""

    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    data: np.ndarray


@dataclass
class ShiftTable:
    """The patterns of one length, sorted by the hash of their last block; pattern p begins at word ``first[p]`` of the items."""

    length: int
    block: int
    items: ItemWords
    first: np.ndarray
    suffix: np.ndarray
    shift: np.ndarray
    #: owner[owner_at[p] : owner_at[p + 1]] are the items of pattern p
    owner_at: np.ndarray
    owner: np.ndarray

    def ends(self, blocks: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        """Word positions where a pattern's last block may end: those that no shift skips."""
        m, mask = self.length, np.uint64(len(self.shift) - 1)
        windows = np.maximum(np.diff(bounds) - m + 1, 0)
        lanes = -(-windows // LANE)
        row = np.repeat(np.arange(len(lanes)), lanes)
        if not len(row):
            return np.empty(0, np.int64)
        nth = np.arange(len(row)) - np.repeat(np.cumsum(lanes) - lanes, lanes)
        at = bounds[row] + m - 1 + nth * LANE
        stop = np.minimum(at + LANE, bounds[row + 1])
        found = []
        while len(at):
            step = self.shift[blocks[at - self.block + 1] & mask].astype(np.int64)
            hit = step == 0
            if hit.any():
                found.append(at[hit])
            at = at + np.maximum(step, 1)
            left = at < stop
            at, stop = at[left], stop[left]
        return np.concatenate(found) if found else np.empty(0, np.int64)

    def occurrences(self, data: np.ndarray, words: bytescan.Words) -> tuple[np.ndarray, np.ndarray]:
        """(position of the last word, pattern) of every occurrence."""
        h = words.hash
        blocks = h if self.block == 1 else bytescan.gram_hash(h, 2)
        ends = self.ends(blocks, words.bounds)
        key = blocks[ends - self.block + 1] if len(ends) else np.empty(0, np.uint64)
        low, high = np.searchsorted(self.suffix, key, "left"), np.searchsorted(self.suffix, key, "right")
        some = high > low
        ends, low, high = ends[some], low[some], high[some]
        out_e, out_p = [], []
        # buckets are walked side by side, one member at a time
        while len(ends):
            same = self.items.hash[self.first[low]] == h[ends - self.length + 1]
            e, p = ends[same], low[same]
            for k in range(1, self.length):
                if not len(e):
                    break
                same = self.items.hash[self.first[p] + k] == h[e - self.length + 1 + k]
                e, p = e[same], p[same]
            out_e.append(e)
            out_p.append(p)
            low = low + 1
            left = low < high
            ends, low, high = ends[left], low[left], high[left]
        if not out_e:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        e, p = np.concatenate(out_e), np.concatenate(out_p)
        sure = np.concatenate([self._same_bytes(data, words, e[k : k + COMPARED], p[k : k + COMPARED]) for k in range(0, len(e), COMPARED)] or [np.empty(0, bool)])
        return e[sure], p[sure]

    def _same_bytes(self, data: np.ndarray, words: bytescan.Words, end: np.ndarray, pattern: np.ndarray) -> np.ndarray:
        """Whether the words up to each ``end`` are the pattern's, byte by byte."""
        span = np.arange(self.length)
        here, there = (end[:, None] - self.length + 1 + span).ravel(), (self.first[pattern][:, None] + span).ravel()
        size = words.end[here] - words.start[here]
        same = size == self.items.end[there] - self.items.start[there]
        size = np.where(same, size, 0)
        within = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        differs = data[np.repeat(words.start[here], size) + within] != self.items.data[np.repeat(self.items.start[there], size) + within]
        same &= np.bincount(np.repeat(np.arange(len(size)), size), differs, len(size)) == 0
        return same.reshape(-1, self.length).all(axis=1)


def compile_tables(texts: pa.Array, window: int) -> list[ShiftTable]:
    """Shift tables, one per pattern length, of the items in ``texts``; owners are row numbers."""
    found, counts, base = [], [], 0
    for part in bytescan.slices(texts):
        words, data = bytescan.scan(part, bytescan.ALNUM), bytescan.LOWER[part.data]
        found.append((words.hash, words.start + base, words.end + base, data))
        counts.append(words.counts)
        base += len(data)
    if not found:
        return []
    items, size = ItemWords(*(np.concatenate(x) for x in zip(*found))), np.concatenate(counts)
    begin = np.cumsum(size) - size
    lengths = np.minimum(size, window)
    out = []
    for m in np.unique(lengths[lengths > 0]).tolist():
        owner = np.flatnonzero(lengths == m)
        many = size[owner] - m + 1
        first = np.repeat(begin[owner] - (np.cumsum(many) - many), many) + np.arange(many.sum())
        out.append(_table(m, items, first, np.repeat(owner, many)))
    return out


def _table(m: int, items: ItemWords, first: np.ndarray, owner: np.ndarray) -> ShiftTable:
    block = min(2, m)
    # equal windows are one pattern: two 64-bit hashes tell them apart
    keys = [np.full(len(first), np.uint64(salt)) for salt in (1, 2)]
    with np.errstate(over="ignore"):
        for k in range(m):
            keys = [bytescan.mix(key * odd + items.hash[first + k]) for key, odd in zip(keys, (np.uint64(0xD6E8FEB86659FD93), np.uint64(0x9E3779B97F4A7C15)))]
    order = np.lexsort((owner, *keys))
    one, two, first, owner = keys[0][order], keys[1][order], first[order], owner[order]
    new = np.r_[True, (one[1:] != one[:-1]) | (two[1:] != two[:-1])] if len(one) else np.empty(0, bool)
    group = np.cumsum(new) - 1
    again = np.r_[False, ~new[1:] & (owner[1:] == owner[:-1])] if len(one) else new
    first, owner, group = first[new], owner[~again], group[~again]
    blocks = items.hash if block == 1 else bytescan.gram_hash(items.hash, 2)
    met = len(np.unique(np.concatenate([blocks[first + j] for j in range(m - block + 1)])))
    shift = np.full(1 << max(12, int(8 * met).bit_length()), m - block + 1, np.uint16 if m < 1 << 16 else np.int64)
    for j in range(m - block + 1):
        # ever nearer to the end, so that the least shift is written last
        shift[blocks[first + j] & np.uint64(len(shift) - 1)] = m - block - j
    suffix = blocks[first + m - block]
    order = np.argsort(suffix, kind="stable")
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    by = np.argsort(place[group], kind="stable")
    at = np.r_[0, np.cumsum(np.bincount(place[group], minlength=len(first)))]
    return ShiftTable(m, block, items, first[order], suffix[order], shift, at, owner[by])


def search(text: pa.Array, tables: list[ShiftTable], names: np.ndarray) -> list[pa.Array]:
    """Per row: word count, hit spans of word positions, names of the items with occurrences."""
    counts, span_at, first, last, item_at, items = [], [np.zeros(1, np.int64)], [], [], [np.zeros(1, np.int64)], []
    for part in bytescan.slices(text):
        words, data = bytescan.scan(part, bytescan.ALNUM), bytescan.LOWER[part.data]
        bounds, n = words.bounds, len(words.hash)
        cover, pairs = np.zeros(n + 1, np.int32), []
        for t in tables:
            e, p = t.occurrences(data, words)
            np.add.at(cover, e - t.length + 1, 1)
            np.add.at(cover, e + 1, -1)
            row = np.searchsorted(bounds, e, "right") - 1
            many = t.owner_at[p + 1] - t.owner_at[p]
            nth = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
            pairs.append(np.stack([np.repeat(row, many), t.owner[np.repeat(t.owner_at[p], many) + nth]]))
        hit = np.cumsum(cover[:n]) > 0
        edge = np.zeros(n + 1, bool)
        edge[bounds] = True
        begin = np.flatnonzero(hit & (edge[:n] | ~np.r_[False, hit[:-1]])) if n else np.empty(0, np.int64)
        stop = np.flatnonzero(hit & (edge[1:] | ~np.r_[hit[1:], False])) if n else np.empty(0, np.int64)
        row = np.searchsorted(bounds, begin, "right") - 1
        counts.append(words.counts)
        first.append(begin - bounds[row])
        last.append(stop - bounds[row])
        span_at.append(np.cumsum(np.bincount(row, minlength=len(part))) + span_at[-1][-1])
        unique = np.unique(np.concatenate(pairs, axis=1), axis=1) if pairs else np.empty((2, 0), np.int64)
        items.append(names[unique[1]])
        item_at.append(np.cumsum(np.bincount(unique[0], minlength=len(part))) + item_at[-1][-1])
    joined = lambda xs, kind=np.int64: np.concatenate(xs) if xs else np.empty(0, kind)
    spans = pa.StructArray.from_arrays([pa.array(joined(first), pa.int64()), pa.array(joined(last), pa.int64())], names=["first", "last"])
    return [
        pa.array(joined(counts), pa.int64()),
        pa.ListArray.from_arrays(pa.array(joined(span_at), pa.int32()), spans),
        pa.ListArray.from_arrays(pa.array(joined(item_at), pa.int32()), pa.array(list(joined(items, object)), pa.string())),
    ]


def find_contamination(docs: DataFrame, items: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW) -> DataFrame:
    """``docs`` with n_words, hit_spans (word positions inside an occurrence) and item_ids (as strings, sorted, distinct).

    Columns of those names are replaced. Null or empty texts have no words and
    no hits; items without words never occur; items with a null id mark spans
    but are not named; repeated rows and items count once each by id. Documents
    never move. The items' bytes are counted first: up to ``BLOCK_BYTES`` make
    one broadcast table, more make one table and pass for each such part.
    """
    chosen = items.select(F.col(item_id).cast("string").alias("id"), F.col(item_text).alias("text"))
    total = chosen.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = -(-total // BLOCK_BYTES) or 1
    spark, out = docs.sparkSession, docs.drop("n_words", "hit_spans", "item_ids")
    for k in range(blocks):
        block = chosen.where(F.pmod(F.xxhash64("id", "text"), F.lit(blocks)) == k).toArrow()
        names = np.array(block["id"].to_pylist(), object)
        table = spark.sparkContext.broadcast((compile_tables(block["text"], window), names))
        fields = [
            T.StructField("n_words", T.LongType()),
            T.StructField(f"__spans{k}", T.ArrayType(SPAN)),
            T.StructField(f"__items{k}", T.ArrayType(T.StringType())),
        ]
        out = map_text(out, text, fields, lambda table=table: lambda column: search(column, *table.value))
    parts = lambda kind: [F.col(f"__{kind}{k}") for k in range(blocks)]
    return out.withColumns(
        {
            "hit_spans": F.array_sort(F.concat(*parts("spans"))),
            "item_ids": F.array_sort(F.array_distinct(F.array_compact(F.concat(*parts("items"))))),
        }
    ).drop(*[f"__{kind}{k}" for kind in ("spans", "items") for k in range(blocks)])


def hit_count(spans: Column) -> Column:
    """Distinct word positions in possibly overlapping, sorted spans."""
    zero = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-1).cast("long").alias("end"))
    return F.aggregate(
        spans,
        zero,
        lambda acc, s: F.struct(
            (acc.n + F.greatest(F.lit(0).cast("long"), s.last - F.greatest(s.first - 1, acc.end))).alias("n"),
            F.greatest(acc.end, s.last).alias("end"),
        ),
        lambda acc: acc.n,
    )
