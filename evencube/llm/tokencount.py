"""Token counts by a transducer compiled from a piece vocabulary.

``merges`` compiles the vocabulary's merge order into a deterministic
transducer over characters whose transitions say how many tokens they add. No
piece runs over a blank's start or a line end, so there the transducer always
falls back to its start: a transition of the coarser machine over segments is
annotated with the count of the segment that it closes, worked out by the
character machine, many segments side by side.

Because every boundary resets the state, the state map of a whole chunk is a
triple: the characters before its first boundary (they finish whatever was
open), the count of what lies between, and the characters after its last
boundary (left open). These maps compose associatively: long texts are cut into
chunks anywhere, tasks map the chunks, and a scan combines the maps pairwise,
level by level.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_text, release, small_batches
from .merges import Transducer

SPACE = "▁"

#: Characters of a chunk, and of a text that is cut into chunks for several tasks.
CHUNK_CHARS, LONG_CHARS = 1 << 18, 1 << 20

#: Transitions kept per task; beyond it they are forgotten and determinised anew.
MAX_ARCS = 400_000

#: Rows whose new segments are compiled together.
BATCH_ROWS = 1_000


class UnsafeVocabulary(ValueError):
    """The vocabulary joins what the segmenter must keep apart, or counts unknown characters in another way."""


@dataclass
class Compiled:
    """A model's transducer over characters, and the tokens of runs of so many blanks, up to a period of them."""

    letters: Transducer
    runs: list[int]
    period: int

    def blanks(self, n: int) -> int:
        whole = max(0, n - len(self.runs) + self.period) // self.period
        return self.runs[n - whole * self.period] + whole * self.runs[self.period]


def _runs(sizes: set[int], n: int) -> int:
    """Tokens of n blanks that join, leftmost first, to pieces of these sizes."""
    parts, k = [1] * n, 0
    while k + 1 < len(parts):
        if parts[k] + parts[k + 1] in sizes:
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
            k = max(k - 1, 0)
        else:
            k += 1
    return len(parts)


def compile_model(model_file: str) -> Compiled:
    """The transducer of a SentencePiece BPE model with byte pieces and no normalisation."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=model_file)
    every = range(model.vocab_size())
    normal = {model.id_to_piece(i): model.get_score(i) for i in every if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))}
    if any(SPACE in p.lstrip(SPACE) or "\n" in p for p in normal) or SPACE not in normal:
        raise UnsafeVocabulary("pieces run over word or line starts")
    if model.normalize(" a  b\né① ") != SPACE * 2 + "a" + SPACE * 2 + "b\né①" + SPACE:
        raise UnsafeVocabulary("the model rewrites texts before it cuts them")
    if sum(model.is_byte(i) for i in every) != 256:
        raise UnsafeVocabulary("unknown characters are not spelled in bytes")
    runs = sorted(len(p) for p in normal if not p.strip(SPACE))
    words = [p for p in normal if len(p) > 1 and p.strip(SPACE)]
    last = min((normal[p] for p in words), default=0.0)
    # blanks join each other last of all, from the left
    if any(p.startswith(SPACE * 2) for p in words) or any(normal[SPACE * k] >= last for k in runs[1:]):
        raise UnsafeVocabulary("pieces of blanks do not come last")
    if len({normal[SPACE * k] for k in runs[1:]}) > 1 or len({normal[p] for p in words}) < len(words):
        raise UnsafeVocabulary("the order of merges is not given by the scores")
    period = runs[-1]
    counts = [_runs(set(runs), n) for n in range(4 * period)]
    if any(counts[n] != counts[n - period] + counts[period] for n in range(2 * period, 4 * period)):
        raise UnsafeVocabulary("pieces of blanks have no period")
    return Compiled(Transducer([p for p in normal if len(p) == 1], sorted(words, key=lambda p: -normal[p])), counts[: 2 * period], period)


class SegmentCounter:
    """Annotated transitions over segments: segment to token count.

    Segments are written as the texts between blanks: ``word`` stands for a
    blank and the word, ``\\nword`` for a line end and a word without a blank,
    and a segment with more blanks than one is spelled out with ``SPACE``.
    """

    def __init__(self, compiled: Compiled) -> None:
        self.compiled = compiled
        self.arcs: dict[str, int] = {}

    def compile(self, segments: Iterable[str]) -> None:
        """Annotate the transitions of segments not met before."""
        segments = set(segments)
        new = [s for s in segments if s not in self.arcs]
        if len(self.arcs) + len(new) > MAX_ARCS:
            self.arcs.clear()
            new = list(segments)
        if not new:
            return
        letters = self.compiled.letters
        rest = [s.lstrip(SPACE) for s in new]
        count, alone = letters.counts([r if r[:1] == "\n" else SPACE + r for r in rest])
        for key, tail, n, single in zip(new, rest, count.tolist(), alone.tolist()):
            blanks = len(key) - len(tail)
            if blanks:
                # all but the blank that the word takes are joined among themselves
                own = n - single if tail else 0
                n = own + self.compiled.blanks(blanks - (1 if tail and not single else 0))
            self.arcs[key] = n


_blank_runs = re.compile(f"(?<=[^{SPACE}\n])(?={SPACE})|(?<=\n)(?={SPACE})|(?=\n)")


def segments_text(text: str) -> str:
    """The text with exactly one blank at every boundary, so that splitting at blanks gives the segments."""
    if "  " not in text and SPACE not in text and text[:1] != " ":
        return text.replace("\n", " \n")
    return " ".join(map(_short, _blank_runs.split(SPACE + text.replace(" ", SPACE))))


def _short(segment: str) -> str:
    """A segment with one leading blank is written without it."""
    return segment[1:] if segment[:1] == SPACE and segment[1:2] != SPACE else segment


@dataclass(frozen=True)
class StateMap:
    """What reading a chunk does to any open segment."""

    head: str
    inner: int
    #: None: the chunk has no boundary, it only extends the open segment by ``head``
    tail: str | None


def compose(a: StateMap, b: StateMap, count: Callable[[str], int]) -> StateMap:
    """The map of reading a's chunk, then b's; ``count`` takes what lies between two boundaries, and may find others in it."""
    if a.tail is None:
        return StateMap(a.head + b.head, b.inner, b.tail)
    if b.tail is None:
        return StateMap(a.head, a.inner, a.tail + b.head)
    return StateMap(a.head, a.inner + count(a.tail + b.head) + b.inner, b.tail)


def scan_maps(maps: Sequence[StateMap], count: Callable[[str], int]) -> StateMap:
    """Composition of all maps by pairwise levels."""
    level = list(maps)
    while len(level) > 1:
        level = [compose(*pair, count) if len(pair) == 2 else pair[0] for pair in (level[k : k + 2] for k in range(0, len(level), 2))]
    return level[0]


class TokenCounter:
    """Counts the tokens of texts through the compiled transitions."""

    def __init__(self, compiled: Compiled) -> None:
        self.segments = SegmentCounter(compiled)

    def counts(self, texts: Sequence[str]) -> list[int]:
        whole = [segments_text(t).split(" ") if t else [] for t in texts]
        met: set[str] = set()
        for words in whole:
            met.update(words)
        self.segments.compile(met)
        of = self.segments.arcs.__getitem__
        return [sum(map(of, words)) for words in whole]

    def between(self, raw: str) -> int:
        """Tokens of characters after which the state is reset; ``raw`` has its blanks spelled out."""
        parts = [_short(s) for s in _blank_runs.split(raw) if s]
        self.segments.compile(parts)
        return sum(self.segments.arcs[s] for s in parts)

    def chunk_map(self, raw: str) -> StateMap:
        parts = _blank_runs.split(raw)
        if len(parts) == 1:
            return StateMap(raw, 0, None)
        inner = [_short(s) for s in parts[1:-1]]
        self.segments.compile(inner)
        return StateMap(parts[0], sum(self.segments.arcs[s] for s in inner), parts[-1])

    def long(self, maps: Sequence[StateMap]) -> int:
        whole = scan_maps(maps, self.between)
        return self.between(whole.head) + (0 if whole.tail is None else whole.inner + self.between(whole.tail))


def count_tokens(docs: DataFrame, model_file: str, text: str = "text", limit: int = 4096) -> DataFrame:
    """``docs`` with n_bytes (UTF-8), n_tokens (as the library's encode without added tokens) and over_limit.

    Columns of those names are replaced. A null text counts as empty: 0 bytes,
    0 tokens. Texts of over ``LONG_CHARS`` characters are cut into chunks that
    several tasks read; repeated rows count alike; an empty table gives an empty
    result. The model is compiled once, on the driver. A model whose vocabulary
    does not allow the segmentation raises ``UnsafeVocabulary``.
    """
    compiled = docs.sparkSession.sparkContext.broadcast(compile_model(model_file))

    def make() -> Callable[[pa.Array], list[pa.Array]]:
        counter = TokenCounter(compiled.value)

        def work(column: pa.Array) -> list[pa.Array]:
            column = pc.fill_null(column, "")
            found: list[int] = []
            for k in range(0, len(column), BATCH_ROWS):
                found += counter.counts(column.slice(k, BATCH_ROWS).to_pylist())
            return [pa.array(found, pa.int64())]

        return work

    names = ("n_bytes", "n_tokens", "over_limit")
    is_long = F.coalesce(F.length(f"`{text}`") > LONG_CHARS, F.lit(False))
    kept = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c.lower() not in names])
    short = map_text(kept.where(~is_long), text, [T.StructField("n_tokens", T.LongType())], make)
    size = F.coalesce(F.octet_length(f"`{text}`"), F.lit(0)).cast("long")
    return short.unionByName(_long_counts(kept.where(is_long), text, compiled)).select(
        *[F.col(f"`{c}`") for c in kept.columns], size.alias("n_bytes"), "n_tokens", (F.col("n_tokens") > limit).alias("over_limit")
    )


def _long_counts(docs: DataFrame, text: str, compiled) -> DataFrame:
    """``docs`` with n_tokens, each text read by as many tasks as it has chunks; a row's columns travel with its first chunk."""
    small_batches(docs.sparkSession)
    plain = [f"c{k}" for k in range(len(docs.columns))]
    rows = docs.toDF(*plain).withColumn("row", F.monotonically_increasing_id())
    at = docs.columns.index(text)
    own = [T.StructField(f.name, f.dataType) for f in rows.schema.fields[:-1]]
    nth = [T.StructField("row", T.LongType()), T.StructField("k", T.IntegerType())]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                one = batch.slice(r, 1)
                whole = one.column(at)[0].as_py()
                for k, first in enumerate(range(0, len(whole), CHUNK_CHARS)):
                    columns = one.columns[:-1] if not k else [pa.nulls(1, c.type) for c in one.columns[:-1]]
                    piece = whole[first : first + CHUNK_CHARS].replace(" ", SPACE)
                    yield pa.RecordBatch.from_arrays([one.column(len(plain)), pa.array([k], pa.int32()), pa.array([piece if k else SPACE + piece]), *columns], names=["row", "k", "piece", *plain])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = TokenCounter(compiled.value)
        for batch in batches:
            maps = [counter.chunk_map(s) for s in batch.column(2).to_pylist()]
            head, inner, tail = zip(*((m.head, m.inner, m.tail) for m in maps)) if maps else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:2], pa.array(head, pa.string()), pa.array(inner, pa.int64()), pa.array(tail, pa.string()), *batch.columns[3:]], names=["row", "k", "head", "inner", "tail", *plain]
            )
        release()

    maps = [T.StructField("head", T.StringType()), T.StructField("inner", T.LongType()), T.StructField("tail", T.StringType())]
    pieces = rows.mapInArrow(cut, T.StructType([*nth, T.StructField("piece", T.StringType()), *own])).repartition("row", "k")
    read_ = pieces.mapInArrow(read, T.StructType([*nth, *maps, *own]))
    met = read_.groupBy("row").agg(F.array_sort(F.collect_list(F.struct("k", "head", "inner", "tail"))).alias("maps"), *[F.first(c, ignorenulls=True).alias(c) for c in plain])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = TokenCounter(compiled.value)
        for batch in batches:
            found = [counter.long([StateMap(m["head"], m["inner"], m["tail"]) for m in maps]) for maps in batch.column(len(plain)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, pa.int64())], names=[*plain, "n_tokens"])

    counted = met.select(*plain, "maps").mapInArrow(scan, T.StructType([*own, T.StructField("n_tokens", T.LongType())]))
    return counted.toDF(*docs.columns, "n_tokens")
