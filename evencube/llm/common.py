"""Shared plumbing of the text operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
from collections.abc import Callable, Iterator, Sequence

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def release() -> None:
    """Gives a worker process's free memory back, as idle workers outlive their task."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)


#: Rows of an Arrow batch of texts; a batch is held several times over, in the JVM and in Python.
BATCH_ROWS = 1_000


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch size (a run-time setting) to ``BATCH_ROWS``, never raises it."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def shared_folder(spark: SparkSession) -> str:
    """The folder for intermediate tables: ``spark.checkpoint.dir``, else the folder set for checkpoints.

    On one machine (tests) a temporary one is set where neither exists; on a
    cluster that raises, as other machines would not see it.
    """
    context = spark.sparkContext
    now = context._jsc.sc().getCheckpointDir()
    named = spark.conf.get("spark.checkpoint.dir", None) or (now.get() if now.isDefined() else None)
    if not named and not context.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
    named = named or tempfile.mkdtemp(prefix="evencube-")
    if now.isEmpty():
        context.setCheckpointDir(named)
    return named


#: Makes Spark drop the shuffle files of a plan once its action is over, not when the driver happens to collect garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def spent_shuffles(spark: SparkSession) -> Iterator[None]:
    """Plans made and run inside leave no shuffle files behind; the session's setting is put back after."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(CLEANUP)
        else:
            spark.conf.set(CLEANUP, before)


def durable(df: DataFrame) -> DataFrame:
    """``df`` with its lineage cut by a reliable checkpoint in the shared folder; what it shuffled is deleted.

    The checkpoint runs a plan of its own, so no other plan loses its shuffles.
    """
    shared_folder(df.sparkSession)
    with spent_shuffles(df.sparkSession):
        return df.select("*").checkpoint(eager=True)


#: Most rows of a few numbers that ``small_side`` broadcasts: some 10 to 40 MB.
BROADCAST_ROWS = 500_000


def small_side(df: DataFrame) -> DataFrame:
    """A checkpointed ``df`` of narrow rows, marked for broadcast if it has ``BROADCAST_ROWS`` at most; larger ones join by shuffle."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def id_remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus`` (null id: null)."""
    return F.crc32(doc_id.cast("string").cast("binary")) % F.lit(modulus)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def map_text(
    df: DataFrame,
    text: str | Sequence[str],
    fields: Sequence[T.StructField],
    make: Callable[[], Callable[..., list[pa.Array]]],
) -> DataFrame:
    """Append columns computed from text columns, batch by batch, keeping rows and other columns.

    ``make`` is called once per task and returns the function from one array per
    column in ``text`` to one array per field. An input column with a result's
    name (as Spark tells names apart) is replaced, as in ``withColumn``; the
    columns in ``text`` are kept.
    """
    small_batches(df.sparkSession)
    inputs = [text] if isinstance(text, str) else list(text)
    names = {f.name.lower() for f in fields}
    if names & {c.lower() for c in inputs}:
        raise ValueError("a result column would replace its input")
    kept = [f.name for f in df.schema.fields if f.name.lower() not in names]
    # plain names inside, as Python stages cannot take names with dots
    source = df.select(*[F.col(f"`{n}`").alias(f"c{k}") for k, n in enumerate(kept)])
    out_names, at = [*source.columns, *(f.name for f in fields)], [kept.index(c) for c in inputs]
    schema = T.StructType([*source.schema.fields, *fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([*batch.columns, *work(*(batch.column(k) for k in at))], names=out_names)
        del work
        release()

    return source.mapInArrow(run, schema).toDF(*kept, *(f.name for f in fields))
