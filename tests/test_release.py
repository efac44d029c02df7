import time

from pyspark.sql import functions as F

from sparkgraphs.core.rounds import Rounds, release
from sparkgraphs.llm import common


def held(spark) -> set:
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {name for i in range(files.size()) if (name := files.apply(i).getName()).startswith("shuffle_")}


def test_the_last_job_s_shuffle_is_let_go(spark):
    """Spark's threads referred to the last job, so its shuffle lay beside the next one's."""
    assert common.release is release
    for i in range(3):
        before = held(spark)
        Rounds(spark, "release").table(spark.range(100_000).withColumn("i", F.lit(i)).repartition("id"))
        mine = held(spark) - before
        assert mine
        release(spark)
        end = time.time() + 5
        while mine & held(spark) and time.time() < end:
            time.sleep(0.1)
        assert not mine & held(spark)
