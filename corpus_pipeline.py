"""From raw documents to packed windows: five stages, each on what the one before kept.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame. All but the
last return the columns of documents; rows with a null id or text pass where
nothing speaks against them. An empty table gives empty results throughout.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evencube.llm.common import durable, shared_folder, spent_shuffles, table
from evencube.llm.decontam import find_contamination
from evencube.llm.neardup import near_duplicates
from evencube.llm.packing import pack
from evencube.llm.quality import MAX_BROADCAST_IDS, fit_quality, score_quality
from evencube.llm.toxicity import fit_toxicity, score_toxicity

#: SQL cannot express the trained stages.
ORACLE_SQL = None


#: Columns that the operators add; documents may have columns of these names too.
ADDED = {"score", "predicted", "model", "loss", "symbols", "perplexity", "kept", "n_words", "hit_spans", "item_ids"}


def _apart(docs: DataFrame) -> DataFrame:
    """``docs`` with columns that an operator would replace put under other names."""
    return docs.withColumnsRenamed({c: f"__own_{c}" for c in docs.columns if c.lower() in ADDED})


def _back(judged: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of ``docs`` from rows judged under ``_apart``'s names."""
    return judged.select(*[F.col(f"`__own_{c}`" if c.lower() in ADDED else f"`{c}`").alias(c) for c in docs.columns])


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model, fitted on the labelled ones, does not predict toxic."""
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))
    return _back(score_toxicity(_apart(docs), model).where("predicted = 0"), docs)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose perplexity lies within their language's limits."""
    apart = _apart(docs)
    model = fit_quality(apart, table(spark, sf_dir, "labels"))
    return _back(score_quality(apart, model).where("kept"), docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five words, 0.8) one row: that of the smallest id.

    A row without an id is compared too; it counts as one of a very large id
    that its text gives. Of rows of the same id and text one stays; rows of the
    same id whose texts differ, and rows without words, pass.
    """
    text = F.col("text")
    large = F.lit(1 << 62).bitwiseOR(F.xxhash64(text).bitwiseAND(F.lit((1 << 62) - 1)))
    words = text.rlike(r"[^\x20\x09-\x0D]")
    keyed = docs.withColumns({"__id": F.coalesce(F.col("doc_id").cast("long"), F.when(words, large)), "__sign": F.when(words, F.struct(F.xxhash64(text), F.xxhash64(F.lit(1), text)))})
    found = near_duplicates(keyed, words=5, percent=80, doc_id="__id")
    dropped = found.where("not kept and doc_id is not null").select(F.col("doc_id").alias("__id")).distinct()
    left, same = keyed.join(dropped, "__id", "left_anti"), ["__id", "__sign"]
    repeated = durable(keyed.where("__sign is not null").groupBy(*same).count().where("count > 1").select(*same))
    n = repeated.count()
    if n:
        repeated = F.broadcast(repeated) if n <= MAX_BROADCAST_IDS else repeated
        # each task leaves one row of a group before they meet
        one = left.join(repeated, same, "left_semi").dropDuplicates(same)
        left = left.join(repeated, same, "left_anti").unionByName(one)
    return left.select(*[f"`{c}`" for c in docs.columns])


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark."""
    found = find_contamination(_apart(docs), table(spark, sf_dir, "benchmark"))
    return _back(found.where(F.size("hit_spans") == 0), docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in windows of 4096 tokens."""
    return pack(docs, public_tokenizers.path("word_bpe_49k.json"), end_id=2)


STAGES = [
    ("toxicity", toxicity),
    ("quality", quality),
    ("near_dedup", near_dedup),
    ("decontaminate", decontaminate),
    ("packing", packing),
]


def _written(df: DataFrame, folder: str) -> DataFrame:
    with spent_shuffles(df.sparkSession):
        df.select("*").write.parquet(folder)
    return df.sparkSession.read.schema(df.schema).parquet(folder)


def _delete(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; between them tables in the shared folder, each deleted once the next is written."""
    folder, last = f"{shared_folder(spark)}/evencube-{uuid.uuid4().hex}", None
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES[:-1]):
        docs = _written(stage(spark, docs, sf_dir), f"{folder}/{k}")
        if last is not None:
            _delete(spark, last)
        last = f"{folder}/{k}"
    return STAGES[-1][1](spark, docs, sf_dir)
