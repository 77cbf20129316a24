"""Language identification by hyperdimensional profiles.

Every symbol has a random vector of +1 and -1; a trigram's vector binds the
first symbol's vector rotated twice, the second's rotated once and the third's
(component-wise product); a text's vector bundles (adds) its trigrams'. A
language's prototype bundles all training texts of that language. Documents go
to the prototype of highest cosine.

Bundling is linear, so a document's product with a prototype is the sum, over
its trigrams, of the trigram vector's product with that prototype: a table of
trigrams by languages, of bounded size, takes the place of the vectors when
documents are scored. Bound trigram vectors are quasi-orthogonal, which gives a
document vector's length: dimensions times the root of summed squared counts.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bytescan
from .common import durable, map_text, small_batches

DIMENSIONS, SEED = 8192, 20_011

#: Symbols: 0 between words, 1-26 letters, 27 digits, 28-63 bytes of other characters by their low bits.
SYMBOLS = 64
_b = np.arange(256)
SYMBOL_OF = np.zeros(256, np.int64)
SYMBOL_OF[97:123] = np.arange(1, 27)
SYMBOL_OF[48:58] = 27
SYMBOL_OF[128:] = 28 + _b[128:] % 36

#: Languages of a block; its table of trigrams takes 64**3 * 4 bytes each.
BLOCK_LANGUAGES = 64


def trigrams(part: bytescan.Slice) -> tuple[np.ndarray, np.ndarray]:
    """(row, trigram code) at every byte; runs between words count as one symbol, rows are padded with it."""
    n, rows = len(part.data), len(part)
    row = np.repeat(np.arange(rows), np.diff(part.offsets))
    symbol = SYMBOL_OF[bytescan.LOWER[part.data]]
    keep = np.ones(n, bool)
    keep[1:] = (symbol[1:] != 0) | (symbol[:-1] != 0) | (row[1:] != row[:-1])
    row, symbol = row[keep], symbol[keep]
    if not len(row):
        return row, symbol
    first = np.r_[True, row[1:] != row[:-1]]
    last = np.r_[row[1:] != row[:-1], True]
    before = np.where(first, 0, np.r_[0, symbol[:-1]])
    after = np.where(last, 0, np.r_[symbol[1:], 0])
    code = (before * SYMBOLS + symbol) * SYMBOLS + after
    useful = symbol != 0
    return row[useful], code[useful]


def symbol_vectors(dimensions: int = DIMENSIONS, seed: int = SEED) -> np.ndarray:
    return (np.random.default_rng(seed).integers(0, 2, (SYMBOLS, dimensions), np.int8) * 2 - 1).astype(np.int8)


def bind(codes: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Vectors of trigrams: rotated twice, rotated once, as is, multiplied."""
    a, b, c = codes // SYMBOLS**2, codes // SYMBOLS % SYMBOLS, codes % SYMBOLS
    return np.roll(vectors, 2, axis=1)[a] * np.roll(vectors, 1, axis=1)[b] * vectors[c]


def _parts(n: int, size: int = 1024) -> Iterator[slice]:
    return (slice(k, k + size) for k in range(0, n, size))


def bundle(counts: Sequence[tuple[np.ndarray, np.ndarray]], vectors: np.ndarray) -> np.ndarray:
    """One vector per language from its (codes, counts): the sum of its trigrams' vectors, by their shares."""
    # a language's size must not matter, only its mix of trigrams
    profile = np.zeros((len(counts), vectors.shape[1]))
    for k, (codes, n) in enumerate(counts):
        share = n / max(n.sum(), 1)
        for part in _parts(len(codes)):
            profile[k] += share[part] @ bind(codes[part], vectors).astype(np.float64)
    return profile


def prototypes(profile: np.ndarray) -> np.ndarray:
    """Unit vectors of what tells the languages apart."""
    if len(profile) > 1:  # what all languages share tells none apart
        profile = profile - profile.mean(axis=0)
    return profile / np.maximum(np.linalg.norm(profile, axis=1, keepdims=True), 1e-12)


class Profiles:
    """Prototypes of a block of languages, ready to score texts; ``codes`` are the trigrams of all training texts."""

    def __init__(self, names: list[str], unit: np.ndarray, codes: np.ndarray, vectors: np.ndarray) -> None:
        self.root, self.names = vectors.shape[1] ** 0.5, names
        # trigrams of no training text would add nothing but the noise of chance products
        self.table = np.zeros((len(names), SYMBOLS**3), np.float32)
        for part in _parts(len(codes)):
            self.table[:, codes[part]] = unit.astype(np.float32) @ bind(codes[part], vectors).astype(np.float32).T

    def cosines(self, part: bytescan.Slice) -> np.ndarray:
        """Cosine of every row (down) with every language (across); rows without symbols: 0."""
        row, code = trigrams(part)
        out = np.zeros((len(part), len(self.names)))
        if not len(row):
            return out
        pair, count = np.unique(row * SYMBOLS**3 + code, return_counts=True)
        of = pair // SYMBOLS**3
        length = np.sqrt(np.bincount(of, count.astype(float) ** 2, len(part))) * self.root
        for k in range(len(self.names)):
            out[:, k] = np.bincount(row, self.table[k][code], len(part))
        return out / np.maximum(length, 1e-12)[:, None]

    def predict(self, text: pa.Array) -> list[pa.Array]:
        languages, scores = [], []
        for part in bytescan.slices(text):
            cosine = self.cosines(part)
            lettered = has_letter(part)
            best = cosine.argmax(axis=1) if self.names else np.zeros(len(part), int)
            for r in range(len(part)):
                known = bool(self.names) and lettered[r]
                languages.append(self.names[best[r]] if known else "und")
                scores.append(float(np.clip((1 + cosine[r, best[r]]) / 2, 0, 1)) if known else 0.0)
        return [pa.array(languages, pa.string()), pa.array(scores, pa.float64())]


def has_letter(part: bytescan.Slice) -> np.ndarray:
    """Whether each row has a letter of any script."""
    ascii_letter = (bytescan.LOWER[part.data] >= 97) & (bytescan.LOWER[part.data] <= 122)
    total = np.r_[0, np.cumsum(ascii_letter)]
    out = total[part.offsets[1:]] > total[part.offsets[:-1]]
    for r in np.flatnonzero(~out).tolist():
        raw = part.data[part.offsets[r] : part.offsets[r + 1]]
        if (raw >= 128).any():
            out[r] = any(map(str.isalpha, raw.tobytes().decode("utf-8", "replace")))
    return out


def count_trigrams(docs: DataFrame, text: str, lang: str) -> DataFrame:
    """(lang, code, n) over whole texts; each task sends one row per language and trigram it met."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            names = batch.column(0).dictionary_encode()
            which = names.indices.to_numpy(zero_copy_only=False)
            for part in bytescan.slices(batch.column(1)):
                row, code = trigrams(part)
                of = which[part.first + row]
                for k in np.unique(of).tolist():
                    got = np.bincount(code[of == k], minlength=SYMBOLS**3)
                    name = names.dictionary[int(k)].as_py()
                    total[name] = total[name] + got if name in total else got
        for name, n in total.items():
            code = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(code), pa.string()), pa.array(code, pa.int32()), pa.array(n[code], pa.int64())], names=["lang", "code", "n"])

    small_batches(docs.sparkSession)
    each = docs.select(F.col(lang).cast("string").alias("lang"), F.col(text).alias("text")).where("lang is not null")
    return each.mapInArrow(run, "lang string, code int, n long").groupBy("lang", "code").agg(F.sum("n").alias("n"))


def fit_profiles(docs: DataFrame, text: str = "text", lang: str = "lang", dimensions: int = DIMENSIONS, seed: int = SEED) -> list[Profiles]:
    """Profiles learned from every text with a non-null language (counts over all of them), in blocks of ``BLOCK_LANGUAGES``.

    The counts that reach the driver at once number at most 64**3 for each
    language of a block. Without any language, every text is ``und``.
    """
    counts, vectors = durable(count_trigrams(docs, text, lang)), symbol_vectors(dimensions, seed)
    names = sorted(r.lang for r in counts.select("lang").distinct().collect())
    blocks = [names[k : k + BLOCK_LANGUAGES] for k in range(0, len(names), BLOCK_LANGUAGES)]
    met, profile = np.zeros(SYMBOLS**3, bool), [np.zeros((0, dimensions))]
    for block in blocks:
        found = counts.where(F.col("lang").isin(block)).toArrow()
        of, code, n = np.array(found["lang"].to_pylist(), object), found["code"].to_numpy().astype(np.int64), found["n"].to_numpy()
        met[code] = True
        order = np.argsort(code, kind="stable")
        profile.append(bundle([(code[order][of[order] == name], n[order][of[order] == name]) for name in block], vectors))
    unit, codes = prototypes(np.concatenate(profile)), np.flatnonzero(met)
    return [Profiles(block, unit[k * BLOCK_LANGUAGES :][: len(block)], codes, vectors) for k, block in enumerate(blocks)]


def predict_language(docs: DataFrame, profiles: list[Profiles], text: str = "text") -> DataFrame:
    """``docs`` with lang_pred and score ((1 + cosine) / 2).

    Columns of those names are replaced. Null texts and texts without a letter
    of any script get ``und`` and score 0; ties go to the first language in
    order; repeated rows are predicted alike; documents never move.
    """
    names, out = [c for c in docs.columns if c.lower() not in ("lang_pred", "score")], docs
    # a pass a block; one is enough for up to BLOCK_LANGUAGES languages
    for k, block in enumerate(profiles or [Profiles([], np.zeros((0, 1)), np.empty(0, np.int64), np.ones((SYMBOLS, 1), np.int8))]):
        shared = docs.sparkSession.sparkContext.broadcast(block)
        fields = [T.StructField(f"__lang{k}", T.StringType()), T.StructField(f"__score{k}", T.DoubleType())]
        out = map_text(out, text, fields, lambda shared=shared: shared.value.predict)
    best = F.col("__score0")
    name = F.col("__lang0")
    for k in range(1, len(profiles)):
        name = F.when(F.col(f"__score{k}") > best, F.col(f"__lang{k}")).otherwise(name)
        best = F.greatest(best, F.col(f"__score{k}"))
    return out.select(*[F.col(f"`{c}`") for c in names], name.alias("lang_pred"), best.alias("score"))
