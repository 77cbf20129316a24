"""Intermediate steps leave no shuffle files behind."""

from pyspark.sql import functions as F

from evencube.llm import common


def _shuffles(spark):
    """Shuffles whose outputs the driver still keeps."""
    kept = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses()
    return {int(k) for k in spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(kept.keySet())}


def test_a_checkpoint_drops_what_it_shuffled(spark):
    plan = spark.range(1000).groupBy((F.col("id") % 100).alias("k")).count()
    before, setting = _shuffles(spark), spark.conf.get(common.CLEANUP, None)
    kept = common.durable(plan)
    assert _shuffles(spark) <= before and spark.conf.get(common.CLEANUP, None) == setting
    assert kept.count() == 100 and plan.count() == 100
