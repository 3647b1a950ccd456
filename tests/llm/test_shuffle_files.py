"""Tables written to the shared folder leave no shuffle files on the executors' disks."""

import time

from pyspark.sql import functions as F

from docprofile.llm.common import DROP_SHUFFLES, materialise


def shuffle_files(spark):
    time.sleep(2)  # they go after the execution has ended
    return spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ").count("shuffle_")


def test_tables_leave_no_shuffle_files(spark):
    was, before = spark.conf.get(DROP_SHUFFLES), shuffle_files(spark)
    counted = materialise(spark.range(100_000).groupBy((F.col("id") % 5000).alias("key")).agg(F.count(F.lit(1)).alias("n")), "counted")
    assert shuffle_files(spark) <= before and spark.conf.get(DROP_SHUFFLES) == was
    assert counted.count() == 5000 and counted.agg(F.sum("n")).first()[0] == 100_000
