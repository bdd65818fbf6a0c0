"""Sessions for tests and notebooks; on a cluster the caller's session is used as it is."""

from __future__ import annotations

from pyspark.sql import SparkSession


def local_session(threads: str = "8", partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session in UTC with adaptive execution."""
    conf = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.driver.memory": memory,
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
    }
    spark = SparkSession.builder.master(f"local[{threads}]").appName("edgefold").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark
