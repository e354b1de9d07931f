"""What saving intermediate tables leaves on disk."""

import time

from pyspark.sql import functions as F

from subwin import storage
from subwin.storage import Scratch


def _shuffles(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {files.apply(i).getName() for i in range(files.size()) if files.apply(i).getName().startswith("shuffle_")}


def test_a_saved_table_leaves_no_shuffle_files(spark):
    before = _shuffles(spark)
    rows = spark.range(10_000).withColumn("x", F.col("id") % 1000)
    saved = Scratch(spark, "test").save(rows.repartition(4, "id").groupBy("x").agg(F.count("*").alias("n")), "counts")
    end = time.time() + 20
    while _shuffles(spark) - before and time.time() < end:
        time.sleep(0.2)
    assert not _shuffles(spark) - before
    assert saved.agg(F.sum("n")).first()[0] == 10_000 and spark.conf.get(storage._CLEANUP, None) is None


def test_the_settings_of_the_session_stay(spark):
    spark.conf.set(storage._CLEANUP, "false")
    try:
        Scratch(spark, "test").save(spark.range(3).repartition(2, "id"), "rows")
        assert spark.conf.get(storage._CLEANUP) == "false"
    finally:
        spark.conf.unset(storage._CLEANUP)
