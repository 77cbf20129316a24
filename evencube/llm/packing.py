"""Packing into windows by Karmarkar-Karp multiway differencing.

Every document becomes its token ids and an end id, cut into whole windows and
a rest; a long rest is cut once more into pieces of bounded size. Rests are
dealt to groups of about ``GROUP_WINDOWS`` windows. In a group every piece
starts as a partial partition with one filled window; the two partial
partitions with the widest spread are merged over and over, the fullest windows
of one onto the emptiest of the other, until one near-equal partition is left.
If any window is over capacity, the number of windows rises and the group is
packed again.
"""

from __future__ import annotations

import functools
import heapq
import json
import re
import zlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, release, small_batches

WINDOW = 4096

#: Longest piece of a document's rest; several meet in a window, which lets differencing even them out.
PIECE = 1024

#: Windows of a group that one task packs.
GROUP_WINDOWS = 256

#: Distinct pieces whose ids are kept per worker process; beyond it they are forgotten and encoded anew.
MAX_KEPT = 700_000

#: Most rows and bytes of text that are encoded together.
BATCH_ROWS, BATCH_BYTES = 1_000, 4 << 20

#: Texts of these characters only (ASCII, letters of Latin-1 and Latin Extended-A) are cut as the vocabulary's own rule cuts them.
PLAIN = re.compile("[\t\n\r -~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u017f]*")

#: Fixed value: the rule, for lower-cased plain texts.
PLAIN_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u017f]+|[0-9]|[!-/:-@\[-`{-~]+")


class PieceEncoder:
    """Ids of texts by a tokenizers file whose merges stay inside pieces and which drops white space.

    The library gives the ids of every distinct piece once; a text's ids are
    its pieces' ids in order. Plain texts are cut to words, single digits and
    runs of signs, others only at blanks and line ends.
    """

    def __init__(self, tokenizer_file: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_file)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        self.special = [str(t) for t in self.tokenizer.get_added_tokens_decoder().values()]
        probe = "Ab  c'll_d9.\n 12\u00c4\u00df'x!'s"
        self.plain = self._ids([probe])[0] == self._ids(["".join(w) for w in PLAIN_PIECES.findall(probe.lower())], joined=True)
        if self._ids(["ab  \n cd"])[0] != self._ids(["ab", "cd"], joined=True):
            raise ValueError("tokens of this vocabulary depend on white space")
        self.kept: dict[str, bytes] = {}
        # ids that close a piece, where the vocabulary marks them
        suffix = json.loads(self.tokenizer.to_str())["model"].get("end_of_word_suffix")
        vocabulary = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)
        self.closes[[i for token, i in vocabulary.items() if suffix and token.endswith(suffix)]] = True

    def _ids(self, texts: Sequence[str], joined: bool = False) -> list:
        found = [list(e.ids) for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]
        return [i for ids in found for i in ids] if joined else found

    def _learn(self, pieces: set[str]) -> None:
        new = [p for p in pieces if p not in self.kept]
        if len(self.kept) + len(new) > MAX_KEPT:
            self.kept.clear()
            new = list(pieces)
        plain = [p for p in new if self.plain and PLAIN_PIECES.fullmatch(p)]
        for k in range(0, len(plain), 100):
            if not self._learn_line(plain[k : k + 100]):
                self._learn_each(plain[k : k + 100])
        met = set(plain)
        self._learn_each([p for p in new if p not in met])

    def _learn_line(self, part: list[str]) -> bool:
        """Ids of many plain pieces from one encoding, told apart by closing ids; false where these do not fit."""
        ids = np.array(self.tokenizer.encode_batch_fast([" ".join(part)], add_special_tokens=False)[0].ids, "<u4")
        ends = np.flatnonzero(self.closes[ids]) + 1
        if len(ends) != len(part) or ends[-1] != len(ids):
            return False
        raw, cuts_ = ids.tobytes(), [0, *(4 * ends).tolist()]
        self.kept.update(zip(part, (raw[a:b] for a, b in zip(cuts_, cuts_[1:]))))
        return True

    def _learn_each(self, part: list[str]) -> None:
        found = [e.ids for e in self.tokenizer.encode_batch_fast(part, add_special_tokens=False)]
        self.kept.update((p, np.array(ids, "<u4").tobytes()) for p, ids in zip(part, found))

    def _cut(self, text: str) -> list[str]:
        if self.plain and PLAIN.fullmatch(text) and not any(t in text for t in self.special):
            return PLAIN_PIECES.findall(text.lower())
        return text.replace("\n", " ").split(" ")

    def encode(self, texts: Sequence[str]) -> list[bytes]:
        """Little-endian 32-bit ids of every text."""
        out, waiting, unknown, get = [], [], set(), self.kept.get
        for row, text in enumerate(texts):
            pieces = self._cut(text)
            found = list(map(get, pieces))
            if None in found:
                unknown.update(p for p, ids in zip(pieces, found) if ids is None)
                waiting.append((row, pieces, found))
                out.append(b"")
            else:
                out.append(b"".join(found))
        self._learn(unknown)
        for row, pieces, found in waiting:
            out[row] = b"".join([self.kept[p] if ids is None else ids for p, ids in zip(pieces, found)])
        return out


@functools.lru_cache(maxsize=2)
def _encoder(tokenizer_file: str) -> PieceEncoder:
    """One encoder per worker process and file, so that tasks share what it has learnt."""
    return PieceEncoder(tokenizer_file)


def cuts(total: int, window: int = WINDOW, piece: int = PIECE) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: whole windows, then its rest in equal parts of at most ``piece``."""
    full = total // window
    out = [(k * window, window) for k in range(full)]
    rest, at = total - full * window, full * window
    parts = -(-rest // piece)
    for k in range(parts):
        stop = full * window + rest * (k + 1) // parts
        out.append((at, stop - at))
        at = stop
    return out


def cut_documents(docs: DataFrame, tokenizer_file: str, end_id: int, window: int, piece: int, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens) of every piece of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = _encoder(tokenizer_file), np.array([end_id], "<u4").tobytes()
        for batch in batches:
            sizes = np.cumsum([0, *pc.fill_null(pc.binary_length(batch.column(1)), 0).to_pylist()])
            row = 0
            while row < batch.num_rows:
                stop = min(row + BATCH_ROWS, max(row + 1, int(np.searchsorted(sizes, sizes[row] + BATCH_BYTES, "right")) - 1), batch.num_rows)
                part = batch.slice(row, stop - row)
                which, start, length, crc, tokens = [], [], [], [], []
                for r, ids in enumerate(encoder.encode([t or "" for t in part.column(1).to_pylist()])):
                    ids += end
                    n = len(ids) // 4
                    for a, m in cuts(n, window, piece):
                        which.append(r)
                        start.append(a)
                        length.append(m)
                        crc.append(zlib.crc32(ids[4 * a : 4 * (a + m)]))
                        tokens.append(n)
                columns = [part.column(0).take(pa.array(which, pa.int64())), *(pa.array(c, pa.int64()) for c in (start, length, crc, tokens))]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])
                row = stop
        release()

    small_batches(docs.sparkSession)
    kind = docs.schema[doc_id].dataType.simpleString()
    source = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    return source.mapInArrow(run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long")


def difference(sizes: Sequence[int], k: int) -> tuple[np.ndarray, int]:
    """(window of each item, fullest window) by k-way differencing of the items."""
    n = len(sizes)
    window = np.zeros(n, np.int64)
    if not n:
        return window, 0
    left, right = [-1] * n, [-1] * n  # a node is an item or two nodes that share a window
    heap: list[tuple[int, int, np.ndarray, np.ndarray]] = []
    for order, i in enumerate(sorted(range(n), key=lambda i: (-sizes[i], i))):
        sums, nodes = np.zeros(k, np.int64), np.full(k, -1, np.int64)
        sums[0], nodes[0] = sizes[i], i
        heap.append((-int(sizes[i]) if k > 1 else 0, order, sums, nodes))
    heapq.heapify(heap)
    order = n
    while len(heap) > 1:
        _, _, a, an = heapq.heappop(heap)
        _, _, b, bn = heapq.heappop(heap)
        b, bn = b[::-1], bn[::-1]  # sums fall, so this lays the emptiest on the fullest
        sums, nodes = a + b, np.where(an < 0, bn, an)
        for at in np.flatnonzero((an >= 0) & (bn >= 0)).tolist():
            left.append(int(an[at]))
            right.append(int(bn[at]))
            nodes[at] = len(left) - 1
        by = np.argsort(-sums, kind="stable")
        sums, nodes = sums[by], nodes[by]
        heapq.heappush(heap, (int(sums[-1] - sums[0]), order, sums, nodes))
        order += 1
    _, _, sums, nodes = heap[0]
    for w, node in enumerate(nodes.tolist()):
        stack = [node] if node >= 0 else []
        while stack:
            at = stack.pop()
            if at < n:
                window[at] = w
            else:
                stack += [left[at], right[at]]
    return window, int(sums[0])


def pack_group(sizes: Sequence[int], capacity: int) -> np.ndarray:
    """Window of each item; the number of windows starts at what the sum needs and rises while one is too full."""
    k = max(1, -(-int(sum(sizes)) // capacity))
    while True:
        window, fullest = difference(sizes, k)
        if fullest <= capacity:
            return window
        k += max(1, -(-k * (fullest - capacity) // (2 * capacity)))


def pack(docs: DataFrame, tokenizer_file: str, end_id: int = 2, window: int = WINDOW, piece: int = PIECE, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text is a document of its end id alone. Repeated rows are
    packed as documents of their own; a null doc_id is kept. An empty table
    gives an empty result; other columns are dropped. Pieces of one window stand
    in order of document and start, without gaps. ``sequence_id`` is unique, not
    consecutive. Groups are dealt row by row, so no document or repeated id
    makes one group large; each holds about ``GROUP_WINDOWS`` windows.
    """
    if not 0 < piece <= window:
        raise ValueError("0 < piece <= window")
    pieces = durable(cut_documents(docs, tokenizer_file, end_id, window, piece, text, doc_id))
    rest = pieces.where(F.col("length") < window)
    total = rest.agg(F.sum("length")).first()[0] or 0
    groups = max(1, round(total / (window * GROUP_WINDOWS)))
    row = F.monotonically_increasing_id()
    # rows that fill a window need no company: odd ids, so that none meets a group's even ones
    full = pieces.where(F.col("length") >= window).select("*", (row * 2 + 1).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    dealt = rest.withColumn("__row", row).withColumn("__group", F.pmod(F.xxhash64("doc_id", "start", "__row"), F.lit(groups)))
    schema = rest.schema.add("sequence_id", "long").add("offset", "long")

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by([("doc_id", "ascending"), ("start", "ascending"), ("__row", "ascending")])
        length = group["length"].to_numpy()
        at = pack_group(length.tolist(), window)
        order = np.argsort(at, kind="stable")
        run_on = np.cumsum(length[order]) - length[order]
        first = np.r_[True, at[order][1:] != at[order][:-1]]
        offset = np.empty(len(at), np.int64)
        offset[order] = run_on - np.maximum.accumulate(np.where(first, run_on, 0))
        base = group["__group"][0].as_py() << 32
        out = group.select(["doc_id", "start", "length", "ids_crc32", "doc_tokens"])
        return out.append_column("sequence_id", pa.array((base + at) * 2)).append_column("offset", pa.array(offset))

    packed = dealt.groupBy("__group").applyInArrow(run, schema)
    return packed.unionByName(full)
