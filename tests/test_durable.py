"""Tables of the shared folder."""

import time

from pyspark.sql import functions as F

from poolcurator.sources.files import CLEANUP, durable


def test_a_written_table_leaves_no_shuffle_files(spark):
    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    held = lambda: disk.getAllFiles().size()
    spark.sparkContext._jvm.System.gc()
    time.sleep(1)
    before = held()
    durable(spark.range(50_000).groupBy((F.col("id") % 9_000).alias("k")).count(), "counted")
    for _ in range(20):
        if held() <= before:
            break
        time.sleep(0.5)
    assert held() <= before
    assert spark.conf.get(CLEANUP, None) in (None, "false")
