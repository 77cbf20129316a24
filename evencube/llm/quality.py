"""Quality classifier: an interpolated modified Kneser-Ney model of trusted text.

Documents are judged by the byte n-grams of ``bytegrams``: counts over all
trusted texts of a language, open and growing with the corpus. A document is
kept when the loss of what its language's trusted texts do not hold lies between
quantiles of the trusted texts', all texts being scored by the other fold's.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bytegrams
from .common import durable, map_text

#: The model for texts without a language of their own.
ANY = ""

#: Trusted texts a language needs for a model of its own.
MIN_TEXTS = 20

#: Quantiles of a language's trusted texts between which documents are kept.
LOW, HIGH = 0.005, 0.995

#: The scatter of a mean loss falls with this power of the number of bytes; bytes of a text go together, so less than by the root.
POWER = 0.25

#: Most labelled ids that are broadcast to find trusted texts; more are joined by shuffle.
MAX_BROADCAST_IDS = 2_000_000

#: Bytes of tables of one broadcast block, about GRAM_BYTES for a gram; more make more blocks, each a pass over the texts.
BLOCK_BYTES, GRAM_BYTES = 128 << 20, 36

#: Shards of a block.
SHARDS = 32

_SUMS = ("loss", "bytes", "fresh_loss", "fresh")


@dataclass
class TextQuality:
    """Trusted texts, and the languages that have a model of their own."""

    docs: DataFrame
    ids: DataFrame
    own: list[str]

    def trusted(self) -> DataFrame:
        """(lang, text) of the documents whose label says quality 1."""
        return self.docs.select("doc_id", F.col("lang").cast("string").alias("lang"), "text").join(self.ids, "doc_id", "left_semi").drop("doc_id")

    def model_of(self, lang: Column) -> Column:
        return F.when(lang.isin(self.own), lang).otherwise(F.lit(ANY)) if self.own else F.lit(ANY)

    def number(self, model: Column, fold: Column) -> Column:
        """Number of a model's fold; that of all languages comes last."""
        place = F.array_position(F.array(*[F.lit(x) for x in [*self.own, ANY]]), model) - 1
        return (2 * place + fold).cast("int")


def fit_quality(docs: DataFrame, labels: DataFrame) -> TextQuality:
    """What a model of the texts that ``labels`` (doc_id, quality) mark with quality 1 is made of, all of them.

    Languages with fewer than ``MIN_TEXTS`` trusted texts, and texts without a
    language, use the model of all languages together. Without any trusted text
    the model keeps everything.
    """
    ids = labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct()
    ids = F.broadcast(ids) if ids.count() <= MAX_BROADCAST_IDS else ids
    trusted = docs.select("doc_id", "lang").join(ids, "doc_id", "left_semi")
    sizes = trusted.where("lang is not null").groupBy("lang").count().where(F.col("count") >= MIN_TEXTS)
    own = sorted(str(r.lang) for r in sizes.collect())
    if 2 * len(own) + 2 > bytegrams.MODELS:
        raise ValueError("more languages of trusted texts than there are model numbers")
    return TextQuality(docs, ids, own)


def _limits(losses: DataFrame) -> DataFrame:
    """(__of, __centre, __low, __high): the trusted texts' median loss a byte, and quantiles of their ``_distance`` from it."""
    full = losses.where("__fresh > 0")
    centre = full.groupBy("__model").agg(F.percentile_approx(F.try_divide("__fresh_loss", "__fresh"), 0.5, 10_000).alias("__centre"))
    far = full.join(F.broadcast(centre), "__model").groupBy("__model", "__centre").agg(F.percentile_approx(_distance(), [LOW, HIGH], 10_000).alias("q"))
    return far.select(F.col("__model").alias("__of"), "__centre", F.col("q")[0].alias("__low"), F.col("q")[1].alias("__high"))


def _distance() -> Column:
    """Mean loss of the fresh bytes less the centre, by a power of their number: the means of few bytes scatter more."""
    size = F.col("__fresh")
    return (F.try_divide(F.col("__fresh_loss"), size) - F.col("__centre")) * F.pow(size, F.lit(POWER))


def _blocks(counts: DataFrame) -> list:
    """Broadcast blocks of the model's tables, each of bounded size."""
    blocks = max(1, -(-counts.count() * GRAM_BYTES // BLOCK_BYTES))
    shards = SHARDS * blocks
    cut, pairs = bytegrams.statistics(counts, shards)
    made = bytegrams.tables(counts, shards, cut, pairs)
    made = durable(made) if blocks > 1 else made
    context, out = counts.sparkSession.sparkContext, []
    for k in range(blocks):
        blobs = made.where(F.pmod("shard", F.lit(blocks)) == k).select("blob").toArrow()["blob"].to_pylist()
        out.append(context.broadcast(bytegrams.Block(blobs, pairs, k, blocks)))
    return out


def _scored(texts: DataFrame, text: str, blocks: list) -> DataFrame:
    """``texts`` (with __number, the model to score by) with __loss, __bytes, __fresh_loss and __fresh."""
    kinds = dict(zip(_SUMS, (T.DoubleType(), T.LongType(), T.DoubleType(), T.LongType())))
    for k, block in enumerate(blocks):
        fields = [T.StructField(f"__{name}{k}", kind) for name, kind in kinds.items()]
        texts = map_text(texts, [text, "__number"], fields, lambda block=block: block.value.score)
    total = {f"__{name}": sum((F.col(f"__{name}{k}") for k in range(1, len(blocks))), F.col(f"__{name}0")) for name in kinds}
    return texts.withColumns(total).drop(*[f"__{name}{k}" for name in kinds for k in range(len(blocks))])


def score_quality(docs: DataFrame, model: TextQuality, text: str = "text", lang: str = "lang") -> DataFrame:
    """``docs`` with model, loss, symbols, perplexity, score and kept.

    ``loss`` is the whole text's negative log probability, ``symbols`` its bytes,
    its end counted as one, ``perplexity`` that of one of them (null for null or
    empty texts, which are kept: nothing speaks against them). The limits are on
    the bytes that end a gram which no trusted text of the other fold has, so
    that near copies of trusted texts do not stretch them, and widen as their
    number falls; ``score`` is 1 at the language's centre and 0 at its limits or
    beyond. Columns of those names are replaced; repeated rows score alike; an
    empty table gives an empty result. Documents never move.
    """
    new = ("model", "loss", "symbols", "perplexity", "score", "kept")
    names = [c for c in docs.columns if c.lower() not in new]
    fold = lambda t: F.pmod(F.xxhash64(F.coalesce(t, F.lit(""))), F.lit(2))
    own = docs.withColumn("__model", model.model_of(F.col(lang).cast("string")))
    trusted = model.trusted().withColumns({"__model": model.model_of(F.col("lang")), "__fold": fold(F.col("text"))})
    if own.where(F.col("__model") == ANY).limit(1).count():
        # the model of all languages is made of all trusted texts
        both = F.explode(F.array_distinct(F.array("__model", F.lit(ANY)))).alias("__model")
        trusted = trusted.select("lang", "text", "__fold", both)
    counts = durable(bytegrams.count(trusted.select(model.number(F.col("__model"), F.col("__fold")).alias("model"), "text")))
    blocks = _blocks(counts)
    number = lambda t: model.number(F.col("__model"), 1 - fold(t))
    known = trusted.select("__model", "text", number(F.col("text")).alias("__number"), F.xxhash64("text").alias("__a"), F.xxhash64(F.lit(1), "text").alias("__b"))
    known = _scored(known, "text", blocks).select("__model", "__a", "__b", *[f"__{name}" for name in _SUMS])
    limits = _limits(durable(known.dropDuplicates(["__model", "__a", "__b"])))
    found = _scored(own.withColumn("__number", number(F.col(text))), text, blocks)
    found = found.join(F.broadcast(limits), F.col("__model") == F.col("__of"), "left")
    far = _distance()
    edge = F.when(far > 0, F.col("__high")).otherwise(F.col("__low"))
    results = [
        F.col("__model").alias("model"),
        F.col("__loss").alias("loss"),
        F.col("__bytes").alias("symbols"),
        F.when(F.col("__bytes") > 0, F.exp(F.try_divide("__loss", "__bytes"))).alias("perplexity"),
        F.coalesce(F.when(far == 0, 1.0).when(edge * far <= 0, 0.0).otherwise(F.greatest(F.lit(0.0), 1 - far / edge)), F.lit(1.0)).alias("score"),
        F.coalesce(far.between(F.col("__low"), F.col("__high")), F.lit(True)).alias("kept"),
    ]
    return found.select(*[F.col(f"`{c}`") for c in names], *results)
