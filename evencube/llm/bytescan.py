"""Vectorised word scanning over the UTF-8 buffers of Arrow string columns.

The word classes of this subpackage are unions of byte classes (every byte of a
multi-byte UTF-8 character is >= 0x80), so words can be found, lower-cased and
hashed on the raw buffer with NumPy, without making a Python string per word.
Whole texts are scanned; a slice only ever ends at a row boundary.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once; a longer single text makes its own slice.
SLICE_BYTES = 1 << 20

_MULT = np.uint64(0x9E3779B97F4A7C15 | 1)
_INV = np.uint64(pow(int(_MULT), -1, 1 << 64))

#: A-Z to a-z, every other byte unchanged.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_b = np.arange(256)
#: ``[^\x20\x09-\x0D]+``
NON_SPACE = ~((_b == 32) | ((_b >= 9) & (_b <= 13)))
#: ``[^\x00-\x2F\x3A-\x60\x7B-\x7F]+`` after lower-casing
ALNUM = ((_b >= 48) & (_b <= 57)) | ((_b >= 97) & (_b <= 122)) | (_b >= 128)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser; spreads polynomial hashes over all bits."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return h ^ (h >> np.uint64(31))


class _Powers:
    """Powers of the multiplier and of its inverse, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << max(16, int(n - 1).bit_length())
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.r_[np.uint64(1), np.full(size - 1, _MULT)], dtype=np.uint64)
                self.down = np.cumprod(np.r_[np.uint64(1), np.full(size - 1, _INV)], dtype=np.uint64)
        return self.up, self.down


_powers = _Powers()


@dataclass
class Slice:
    """Rows ``first .. first + len(offsets) - 2`` of a column; ``data`` holds their bytes."""

    first: int
    data: np.ndarray
    offsets: np.ndarray

    def __len__(self) -> int:
        return len(self.offsets) - 1


@dataclass
class Words:
    """Words of a slice in text order: byte ``start``/``end``, 64-bit hash, row bounds."""

    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    #: word ``bounds[r] .. bounds[r+1]-1`` belong to row r
    bounds: np.ndarray
    #: running polynomial sum over the slice's bytes, for hashes of parts of words
    running: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.bounds)

    @property
    def row(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.bounds) - 1), self.counts)

    def prefix_hash(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(word, hash of its first ``size`` bytes) for the words longer than that."""
        word = np.flatnonzero(self.end - self.start > size)
        start = self.start[word]
        if not len(word):
            return word, np.empty(0, np.uint64)
        with np.errstate(over="ignore"):
            return word, mix((self.running[start + size] - self.running[start]) * _powers.down[start] + np.uint64(size))


def slices(column: pa.Array | pa.ChunkedArray, limit: int = SLICE_BYTES) -> Iterator[Slice]:
    """Slices of a string column; null counts as empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.type != pa.large_string():
        column = column.cast(pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, "")
    if not len(column):
        return
    _, off, buf = column.buffers()
    offsets = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(buf, np.uint8) if buf is not None and buf.size else np.empty(0, np.uint8)
    row = 0
    while row < len(column):
        stop = int(np.searchsorted(offsets, offsets[row] + limit, "right")) - 1
        stop = min(max(stop, row + 1), len(column))
        yield Slice(row, data[offsets[row] : offsets[stop]], offsets[row : stop + 1] - offsets[row])
        row = stop


def scan(part: Slice, word_bytes: np.ndarray, lower: bool = True, hashed: bool = True) -> Words:
    """Maximal runs of ``word_bytes`` in each row, with hashes of the (lower-cased) bytes."""
    data = LOWER[part.data] if lower else part.data
    n = len(data)
    inside = np.empty(n + 1, bool)
    inside[:n] = word_bytes[data]
    inside[n] = False
    change = np.empty(n + 1, bool)
    change[0] = n > 0 and inside[0]
    np.not_equal(inside[1:], inside[:-1], out=change[1:])
    edges = np.flatnonzero(change)
    start, end = edges[0::2], edges[1::2]
    # a word that runs over a row's end is cut there
    cuts = part.offsets[1:-1]
    cuts = np.unique(cuts[(cuts > 0) & (cuts < n)])
    if len(cuts):
        cuts = cuts[inside[cuts] & inside[cuts - 1]]
        if len(cuts):
            start, end = np.sort(np.r_[start, cuts]), np.sort(np.r_[end, cuts])
    bounds = np.searchsorted(start, part.offsets)
    h = total = np.empty(0, np.uint64)
    if hashed and len(start):
        up, down = _powers.upto(n + 1)
        total = np.empty(n + 1, np.uint64)
        total[0] = 0
        with np.errstate(over="ignore"):
            np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n], dtype=np.uint64, out=total[1:])
            h = mix((total[end] - total[start]) * down[start])
    return Words(start, end, h, bounds, total)


def word_hash(word: str) -> int:
    """The hash that ``scan`` gives one word (already lower-cased)."""
    raw = np.frombuffer(word.encode(), np.uint8)
    up, _ = _powers.upto(len(raw) + 1)
    with np.errstate(over="ignore"):
        return int(mix(((raw.astype(np.uint64) + np.uint64(1)) * up[: len(raw)]).sum(dtype=np.uint64, keepdims=True))[0])


def gram_hash(h: np.ndarray, n: int) -> np.ndarray:
    """Hashes of every run of ``n`` consecutive words; position i covers words i .. i+n-1."""
    if len(h) < n:
        return np.empty(0, np.uint64)
    with np.errstate(over="ignore"):
        out = h[: len(h) - n + 1].copy()
        for k in range(1, n):
            out = out * np.uint64(0xD6E8FEB86659FD93) + h[k : len(h) - n + 1 + k]
        return mix(out)


def shingles(words: Words, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of each row's distinct n-word shingles, sorted; a shorter row's whole sequence is its one shingle."""
    counts, rows, hashes = words.counts, [], []
    g = gram_hash(words.hash, n)
    if len(g):
        row = words.row
        whole = row[: len(g)] == row[n - 1 :]
        rows.append(row[: len(g)][whole])
        hashes.append(g[whole])
    for size in range(1, n):
        short = np.flatnonzero(counts == size)
        if len(short):
            g = gram_hash(words.hash, size)
            rows.append(short)
            hashes.append(g[words.bounds[short]] ^ np.uint64(size))
    if not rows:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    row, h = np.concatenate(rows), np.concatenate(hashes)
    order = np.lexsort((h, row))
    row, h = row[order], h[order]
    keep = np.ones(len(row), bool)
    keep[1:] = (row[1:] != row[:-1]) | (h[1:] != h[:-1])
    return row[keep], h[keep]
