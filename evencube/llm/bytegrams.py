"""Interpolated modified Kneser-Ney model over byte n-grams, counted and discounted in shards.

A gram is six bytes of a text, A-Z lower-cased, with edges before and after it;
the grams are open, so their number grows with the corpus. Each task sends the
distinct grams of its trusted texts once. All orders from three up of a gram,
and their contexts, hold the two bytes before the last: shards of those two
bytes have everything that these orders need, and only the orders below, at
most 65,536 pairs a model, are summed over the shards. Texts fall into two
folds by their hash; a text is scored by the counts of the other fold's trusted
texts, so that trusted and other texts are scored alike.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bytescan
from .common import release, small_batches

#: Bytes of a gram; a gram and its model's number share 64 bits.
ORDER = 6

#: Model numbers (languages times two folds) that the other bits can tell apart.
MODELS = 1 << 16

#: Grams of trusted texts that a task gathers before it sends them.
SEND = 1_000_000

#: Bytes of text handled at once, each as a gram of eight bytes in several arrays.
SLICE = 1 << 18

#: Orders whose grams hold the two bytes that a shard is chosen by.
SHARDED = range(3, ORDER + 1)

_EIGHT = np.uint64(8)


def _low(gram: np.ndarray, order: int) -> np.ndarray:
    """The model and the last ``order`` bytes of grams."""
    return gram & np.uint64((1 << 8 * order) - 1 | (MODELS - 1) << 48)


def _context(gram: np.ndarray) -> np.ndarray:
    """The model and all bytes but the last."""
    return (gram & np.uint64((MODELS - 1) << 48)) | ((gram & np.uint64((1 << 48) - 1)) >> _EIGHT)


def grams(part: bytescan.Slice, model: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(gram, row) of every byte of every text and of its end; an empty text has none. ``model`` is each row's."""
    size = np.diff(part.offsets)
    full = np.where(size > 0, size + ORDER, 0)
    start = np.cumsum(full) - full
    row = np.repeat(np.arange(len(size), dtype=np.int32), size)
    data = np.zeros(int(full.sum()), np.uint64)
    data[start[row] + ORDER - 1 + np.arange(len(row)) - part.offsets[row]] = bytescan.LOWER[part.data]
    gram = data.copy()
    for k in range(1, ORDER):
        gram[k:] |= data[: len(data) - k] << np.uint64(8 * k)
    of = np.repeat(np.arange(len(size), dtype=np.int32), full)
    last = np.flatnonzero(np.arange(len(data)) - start[of] >= ORDER - 1)
    row = of[last]
    return gram[last] | (model.astype(np.uint64) << np.uint64(48))[row], row


def _merge(gram: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    found, inverse = np.unique(gram, return_inverse=True)
    return found, np.bincount(inverse, n, len(found)).astype(np.int64)


def count(trusted: DataFrame) -> DataFrame:
    """(gram, n) of ``trusted`` (model number, text): distinct grams under their own model number, over whole texts."""
    small_batches(trusted.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def out() -> pa.RecordBatch:
            gram, n = _merge(*(np.concatenate(x) for x in zip(*parts)))
            return pa.RecordBatch.from_arrays([pa.array(gram.view(np.int64)), pa.array(n)], names=["gram", "n"])

        for batch in batches:
            model = batch.column(0).to_numpy(zero_copy_only=False)
            for part in bytescan.slices(batch.column(1), SLICE):
                found = np.unique(grams(part, model[part.first : part.first + len(part)])[0], return_counts=True)
                parts.append(found)
                size += len(found[0])
            if size > SEND:
                gram, n = _merge(*(np.concatenate(x) for x in zip(*parts)))
                parts, size = [(gram, n)], len(gram)
                if size > SEND // 2:
                    yield out()
                    parts, size = [], 0
        if parts:
            yield out()
        release()

    return trusted.select("model", "text").mapInArrow(run, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def discounts(t: np.ndarray) -> np.ndarray:
    """Modified Kneser-Ney discounts from how many grams have counts 1 to 4."""
    y = t[0] / (t[0] + 2 * t[1]) if t[0] else 0.0
    raw = [k - (k + 1) * y * t[k] / t[k - 1] if t[0] and t[k - 1] else 0.0 for k in (1, 2, 3)]
    # too few grams to tell: the usual absolute discount
    return np.array([r if 0 < r < k else 0.6 + 0.3 * (k - 1) for k, r in zip((1, 2, 3), raw)])


def levels(gram: np.ndarray, n: np.ndarray, lowest: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(order, grams, counts) from the highest down; lower orders count in how many words-before theirs are seen."""
    order = np.argsort(gram)
    gram, n = gram[order], n[order]
    for k in range(ORDER, lowest - 1, -1):
        if k < ORDER:
            gram, n = np.unique(_low(gram, k), return_counts=True)
        yield k, gram, n


def _discounted(gram: np.ndarray, n: np.ndarray, cut: dict[int, np.ndarray], below: Callable[[np.ndarray], np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(p of every gram, contexts, mass that each leaves to the order below, whose p ``below`` gives)."""
    if not len(gram):
        return np.empty(0), gram, np.empty(0)
    models, of = np.unique(gram >> np.uint64(48), return_inverse=True)
    less = np.minimum(np.array([cut[m] for m in models.tolist()])[of, np.minimum(n, 3) - 1], n)
    context, at = np.unique(_context(gram), return_inverse=True)
    total = np.bincount(at, n)
    rest = np.bincount(at, less) / total
    return (n - less) / total[at] + rest[at] * below(gram), context, rest


def _bytes(part: dict[str, np.ndarray]) -> bytes:
    return b"".join(len(x).to_bytes(8, "little") + np.ascontiguousarray(x).tobytes() for x in part.values())


_KIND = {"p": "<f4", "r": "<f4", "g": "<u8", "c": "<u8"}
_NAMES = [f"{kind}{k}" for k in SHARDED for kind in "gpcr"]


def _parts(blob: bytes) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for name in _NAMES:
        kind = np.dtype(_KIND[name[0]])
        size = int.from_bytes(blob[at : at + 8], "little") * kind.itemsize
        out[name] = np.frombuffer(blob, kind, size // kind.itemsize, at + 8)
        at += 8 + size
    return out


def shard_of(gram: np.ndarray, shards: int) -> np.ndarray:
    """Shard of the model and of the two bytes before a gram's last."""
    return (bytescan.mix((gram >> np.uint64(48) << np.uint64(16)) | ((gram >> _EIGHT) & np.uint64(0xFFFF))) % np.uint64(shards)).astype(np.int32)


class Pairs:
    """The orders one and two of all models."""

    def __init__(self, gram: np.ndarray, n: np.ndarray) -> None:
        gram, n = gram.view(np.uint64), np.asarray(n, np.int64)
        one, m = np.unique(_low(gram, 1), return_counts=True)
        cuts = []
        for g, c in ((one, m), (gram, n)):
            of = g >> np.uint64(48)
            cuts.append({int(x): discounts(np.array([((of == x) & (c == k)).sum() for k in (1, 2, 3, 4)])) for x in np.unique(of)})
        p1, _, rest = _discounted(one, m, cuts[0], lambda g: np.full(len(g), 1 / 256))
        self.one, self.p1 = one, p1
        self.left = dict(zip((np.unique(one >> np.uint64(48))).tolist(), (rest / 256).tolist()))
        self.gram = np.sort(gram)
        self.p2, self.context, self.rest = _discounted(self.gram, n[np.argsort(gram)], cuts[1], self._first)

    def _first(self, gram: np.ndarray) -> np.ndarray:
        found, hit = _look(self.one, self.p1, _low(gram, 1))
        models, of = np.unique(gram >> np.uint64(48), return_inverse=True)
        return np.where(hit, found, np.array([self.left.get(m, 1 / 256) for m in models.tolist()])[of] if len(gram) else 0.0)

    def __call__(self, gram: np.ndarray) -> np.ndarray:
        """Probability of the last byte of ``gram`` after the one before it."""
        pair = _low(gram, 2)
        found, hit = _look(self.gram, self.p2, pair)
        rest, seen = _look(self.context, self.rest, _context(pair))
        return np.where(hit, found, np.where(seen, rest, 1.0) * self._first(gram))


def _look(keys: np.ndarray, values: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(values of the asked keys, whether they are there)."""
    if not len(keys):
        return np.zeros(len(asked)), np.zeros(len(asked), bool)
    at = np.minimum(np.searchsorted(keys, asked), len(keys) - 1)
    return values[at].astype(float), keys[at] == asked


def statistics(counts: DataFrame, shards: int) -> tuple[dict[int, dict[int, np.ndarray]], Pairs]:
    """(discounts by order and model, the lowest orders) of ``counts``; at most 65,536 rows a model come to the driver."""

    def run(shard: pa.Table) -> pa.Table:
        order, model, n, gram = [], [], [], []
        for k, g, c in levels(shard["gram"].to_numpy().view(np.uint64), shard["n"].to_numpy(), 3):
            of = (g >> np.uint64(48)).astype(np.int64)
            for m in np.unique(of).tolist():
                for v in (1, 2, 3, 4):
                    order.append(k)
                    model.append(m)
                    gram.append(v)
                    n.append(int(((of == m) & (c == v)).sum()))
        pairs, m = np.unique(_low(g, 2), return_counts=True)
        return pa.table({
            "level": pa.array([*order, *[2] * len(pairs)], pa.int32()),
            "model": pa.array([*model, *[0] * len(pairs)], pa.int64()),
            "key": pa.array([*gram, *pairs.view(np.int64).tolist()], pa.int64()),
            "n": pa.array([*n, *m.tolist()], pa.int64()),
        })

    found = dealt(counts, shards).groupBy("shard").applyInArrow(run, "level int, model long, key long, n long")
    got = found.groupBy("level", "model", "key").agg(F.sum("n").alias("n")).toArrow()
    level, model, key, n = (got[c].to_numpy() for c in ("level", "model", "key", "n"))
    cut: dict[int, dict[int, np.ndarray]] = {}
    for k in SHARDED:
        cut[k] = {}
        for m in np.unique(model[level == k]).tolist():
            mine = (level == k) & (model == m)
            cut[k][m] = discounts(n[mine][np.argsort(key[mine])])
    return cut, Pairs(key[level == 2], n[level == 2])


def dealt(counts: DataFrame, shards: int) -> DataFrame:
    """``counts`` with the shard of each gram."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gram = batch.column(0).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(shard_of(gram.view(np.uint64), shards))], names=["gram", "n", "shard"])

    return counts.select("gram", "n").mapInArrow(run, "gram long, n long, shard int")


def tables(counts: DataFrame, shards: int, cut: dict[int, dict[int, np.ndarray]], pairs: Pairs) -> DataFrame:
    """(shard, blob): probabilities and contexts' rests of all orders from three up."""
    shared = counts.sparkSession.sparkContext.broadcast((cut, pairs))

    def run(shard: pa.Table) -> pa.Table:
        cuts, low = shared.value
        found: dict[str, np.ndarray] = {}
        below: Callable[[np.ndarray], np.ndarray] = low
        for k, g, c in reversed(list(levels(shard["gram"].to_numpy().view(np.uint64), shard["n"].to_numpy(), 3))):
            p, context, rest = _discounted(g, c, cuts[k], below)
            found |= {f"g{k}": g, f"p{k}": p.astype("<f4"), f"c{k}": context, f"r{k}": rest.astype("<f4")}
            below = lambda gram, g=g, p=p, k=k: _look(g, p, _low(gram, k))[0]
        return pa.table({"shard": shard["shard"].combine_chunks()[:1], "blob": pa.array([_bytes({x: found[x] for x in _NAMES})], pa.binary())})

    return dealt(counts, shards).groupBy("shard").applyInArrow(run, "shard int, blob binary")


class Block:
    """The tables of the shards of one block, and the lowest orders of all."""

    def __init__(self, blobs: list[bytes], pairs: Pairs, nth: int, blocks: int) -> None:
        self.pairs, self.nth, self.blocks = pairs, nth, blocks
        parts = [_parts(b) for b in blobs]
        self.of: dict[str, np.ndarray] = {}
        for k in SHARDED:
            for key, value in (("g", "p"), ("c", "r")):
                keys, values = (np.concatenate([p[f"{x}{k}"] for p in parts] or [np.empty(0, _KIND[x])]) for x in (key, value))
                order = np.argsort(keys)
                self.of[f"{key}{k}"], self.of[f"{value}{k}"] = keys[order], values[order]

    def losses(self, gram: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(negative log probability, whether the whole gram is unseen) of sorted grams."""
        p, weight, left, fresh = np.empty(len(gram)), np.ones(len(gram)), np.arange(len(gram)), np.zeros(len(gram), bool)
        for k in reversed(SHARDED):
            low = _low(gram[left], k)
            found, hit = _look(self.of[f"g{k}"], self.of[f"p{k}"], low)
            p[left[hit]] = weight[left[hit]] * found[hit]
            left, low = left[~hit], low[~hit]
            if k == ORDER:
                fresh[left] = True
            rest, seen = _look(self.of[f"c{k}"], self.of[f"r{k}"], _context(low))
            weight[left] *= np.where(seen, rest, 1.0)
        p[left] = weight[left] * self.pairs(gram[left])
        return -np.log(np.maximum(p, 1e-30)), fresh

    def score(self, text: pa.Array, model: pa.Array) -> list[pa.Array]:
        """Per text: loss, bytes, loss of fresh bytes and their number, of the bytes that this block knows; each text counts its end."""
        numbers, out = model.to_numpy(zero_copy_only=False), []
        for part in bytescan.slices(text, SLICE):
            gram, row = grams(part, numbers[part.first : part.first + len(part)])
            if self.blocks > 1:
                mine = shard_of(gram, self.blocks) == self.nth
                gram, row = gram[mine], row[mine]
            found, at = np.unique(gram, return_inverse=True)
            loss, fresh = (x[at] for x in self.losses(found)) if len(found) else (np.empty(0), np.empty(0, bool))
            out.append(np.stack([np.bincount(row, x, len(part)) for x in (loss, np.ones(len(row)), loss * fresh, fresh)]).astype(float))
        loss, size, fresh_loss, fresh = np.concatenate(out, axis=1) if out else np.empty((4, 0))
        return [pa.array(loss), pa.array(size.astype(np.int64)), pa.array(fresh_loss), pa.array(fresh.astype(np.int64))]
