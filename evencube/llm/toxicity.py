"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features are the presence of words, of word stems (first bytes, for languages
that compound), of word pairs and of pairs with one word between, hashed to a
fixed range. FTRL-proximal keeps a learning rate per coordinate and
its L1 term leaves most weights at exactly zero, so that the model is a short
list of weights which every task receives.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bytescan
from .common import map_text, release, small_batches

#: Hash range of features; also bounds the model at 2**BITS weights.
BITS = 22

#: Most labelled rows that a fit uses: those with the smallest hash of their id.
MAX_TRAIN_ROWS = 8_000

#: Bytes of their texts; batches of later rows are left out.
MAX_TRAIN_BYTES = 256 << 20

#: Bytes of the stems that count as features beside whole words.
STEMS = (4, 5, 6, 7)

THRESHOLD = 0.7


@dataclass(frozen=True)
class Ftrl:
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 8.0
    l2: float = 0.2
    epochs: int = 5
    #: texts of the sample that must hold a feature before it gets a coordinate
    min_texts: int = 8


def features(part: bytescan.Slice) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature) of every word, stem, pair and pair with a gap, repeats included."""
    words = bytescan.scan(part, bytescan.ALNUM)
    h, row = words.hash, words.row
    rows, keys = [row], [h]
    for size in STEMS:
        word, key = words.prefix_hash(size)
        rows.append(row[word])
        keys.append(key)
    with np.errstate(over="ignore"):
        for gap, salt in ((1, 0xA0761D6478BD642F), (2, 0xE7037ED1A0B428DB)):
            if len(h) > gap:
                same = row[gap:] == row[:-gap]
                rows.append(row[gap:][same])
                keys.append(bytescan.mix(h[:-gap] * np.uint64(salt) + h[gap:])[same])
    key = np.concatenate(keys) >> np.uint64(64 - BITS)
    return np.concatenate(rows), key.astype(np.int64)


def _present(part: bytescan.Slice) -> tuple[np.ndarray, np.ndarray]:
    """``features`` without repeats in a row, by row."""
    row, key = features(part)
    pair = np.unique(row << BITS | key)
    return pair >> BITS, pair & ((1 << BITS) - 1)


def _sigmoid(x: np.ndarray | float) -> np.ndarray | float:
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


def train(texts: pa.Array, labels: np.ndarray, how: Ftrl) -> tuple[np.ndarray, np.ndarray, float]:
    """(features, weights, bias): the non-zero weights after the passes over the texts in their order."""
    held = np.zeros(1 << BITS, np.int32)
    parts = []
    for part in bytescan.slices(texts):
        row, found = _present(part)
        np.add.at(held, found, 1)
        parts.append((row.astype(np.int32), found.astype(np.int32), len(part)))
    key = np.flatnonzero(held >= how.min_texts)
    place = np.full(1 << BITS, -1, np.int32)
    place[key] = np.arange(len(key))
    sizes, places = [np.zeros(1, np.int64)], [np.empty(0, np.int32)]
    while parts:
        row, found, n_rows = parts.pop(0)
        at = place[found]
        sizes.append(np.bincount(row[at >= 0], minlength=n_rows))
        places.append(at[at >= 0])
    bounds, at = np.cumsum(np.concatenate(sizes)), np.concatenate(places)
    del held, place, places
    # the last coordinate is the bias, free of L1
    z, n = np.zeros(len(key) + 1), np.zeros(len(key) + 1)
    l1 = np.r_[np.full(len(key), how.l1), 0.0]

    def weight(i: np.ndarray) -> np.ndarray:
        zi = z[i]
        return np.where(np.abs(zi) <= l1[i], 0.0, -(zi - np.sign(zi) * l1[i]) / ((how.beta + np.sqrt(n[i])) / how.alpha + how.l2))

    for _ in range(how.epochs):
        for r, label in enumerate(labels.tolist()):
            i = np.r_[at[bounds[r] : bounds[r + 1]], len(key)]
            w = weight(i)
            g = float(_sigmoid(w.sum())) - label
            sigma = (np.sqrt(n[i] + g * g) - np.sqrt(n[i])) / how.alpha
            z[i] += g - sigma * w
            n[i] += g * g
    w = weight(np.arange(len(key) + 1))
    used = np.flatnonzero(w[:-1])
    return key[used], w[used], float(w[-1])


@dataclass
class ToxicityModel:
    key: np.ndarray
    weight: np.ndarray
    bias: float

    def scorer(self):
        dense = np.zeros(1 << BITS, np.float32)
        dense[self.key] = self.weight

        def score(text: pa.Array) -> list[pa.Array]:
            out = []
            for part in bytescan.slices(text):
                row, key = features(part)
                hit = dense[key] != 0
                pair = np.unique(row[hit] << BITS | key[hit])
                total = np.bincount(pair >> BITS, dense[pair & ((1 << BITS) - 1)], len(part))
                out.append(_sigmoid(total + self.bias))
            value = np.concatenate(out) if out else np.empty(0)
            return [pa.array(value, pa.float64()), pa.array((value >= THRESHOLD).astype(np.int32), pa.int32())]

        return score


def fit_toxicity(docs: DataFrame, labels: DataFrame, allowed: Column | None = None, how: Ftrl = Ftrl(), max_rows: int = MAX_TRAIN_ROWS) -> ToxicityModel:
    """A model from labelled texts: ``labels`` (doc_id, toxic), where ``allowed`` (a condition on doc_id) holds.

    At most ``max_rows`` labelled ids take part, those with the smallest hash,
    and of them batches up to ``MAX_TRAIN_BYTES``; their whole texts are read,
    one row an id. Null labels and ids without a document are left
    out. One task trains on that bounded sample, in hash order, so a lost
    executor repeats the same result. Without any labelled text the model is
    neutral (score 0.5).
    """
    small_batches(docs.sparkSession)
    rank = F.xxhash64("doc_id")
    known = labels.where("toxic is not null and doc_id is not null")
    if allowed is not None:
        known = known.where(allowed)
    chosen = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(rank, "doc_id").limit(max_rows)
    sample = (
        docs.select("doc_id", "text")
        .join(F.broadcast(chosen), "doc_id")
        # of repeated rows one, so that the bound on ids bounds the rows
        .groupBy(rank.alias("rank"), "doc_id")
        .agg(F.min("text").alias("text"), F.max("toxic").cast("int").alias("toxic"))
        .repartition(1)
        .sortWithinPartitions("rank", "doc_id", "text")
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size = [], 0
        for batch in batches:
            size += batch.column(2).nbytes
            if rows and size > MAX_TRAIN_BYTES:
                break
            rows.append(batch)
        if not rows:
            return
        whole = pa.Table.from_batches(rows)
        rows.clear()
        key, weight, bias = train(whole["text"], whole["toxic"].to_numpy().astype(float), how)
        del whole
        release()
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[-1, key], pa.int64()), pa.array(np.r_[bias, weight], pa.float64())], names=["key", "weight"])

    found = sample.mapInArrow(run, "key long, weight double").toArrow()
    key, weight = found["key"].to_numpy(), found["weight"].to_numpy()
    return ToxicityModel(key[key >= 0], weight[key >= 0], float(weight[key < 0].sum()))


def score_toxicity(docs: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """``docs`` with score (0 to 1) and predicted (1 from ``THRESHOLD`` on).

    Columns of those names are replaced. Whole texts are scored where they lie;
    null and empty texts get the score of the bias alone; repeated rows score
    alike; an empty table gives an empty result. The model (at most 2**BITS
    weights) is broadcast.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]
    return map_text(docs, text, fields, lambda: shared.value.scorer())
