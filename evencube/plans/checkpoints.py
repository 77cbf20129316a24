"""Cutting lineage so that a lost executor costs little."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


def durable(df: DataFrame) -> DataFrame:
    """``df`` from a reliable checkpoint in the folder of ``spark.checkpoint.dir``.

    Where none is set, one machine (tests) uses a temporary folder; a cluster
    raises, as its machines would not share one.
    """
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        named = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="evencube-"))
    return df.checkpoint(eager=True)
