"""The given parquet tables, and designs as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_design(points: DataFrame, path: str, by: list[str] | None = None, form: str = "parquet") -> None:
    """A design or its strata in any of Spark's file formats, optionally partitioned (by replication, say)."""
    writer = points.write.mode("overwrite").format(form)
    (writer.partitionBy(*by) if by else writer).save(path)


def read_design(spark: SparkSession, path: str, form: str = "parquet", schema: str | None = None) -> DataFrame:
    reader = spark.read.format(form)
    return (reader.schema(schema) if schema else reader).load(path)
