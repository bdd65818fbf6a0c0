"""Intermediate tables: what stays behind once they are written."""

import time
from pathlib import Path

from pyspark.sql import functions as F

from edgefold.runtime.scratch import RELEASE, save


def test_written_tables_leave_no_shuffle_files(spark):
    def held() -> int:
        return sum(f.stat().st_size for f in Path(spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()[0]).rglob("shuffle_*.data"))

    before = spark.conf.get(RELEASE)
    df = spark.range(500_000).select(F.xxhash64("id").alias("k"), "id").groupBy("k").agg(F.max("id").alias("top"))
    floor = held()
    first = save(df, "once")
    for _ in range(50):  # files go in the background
        if held() <= floor:
            break
        time.sleep(0.1)
    assert held() <= floor and spark.conf.get(RELEASE) == before
    again = save(df, "twice")
    assert first.exceptAll(again).count() == 0 and again.count() == 500_000
