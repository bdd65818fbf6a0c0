"""Event streams over the ``events`` table: windows, sessions, deduplication, joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime.scratch import new_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table as a file stream with a stated schema; ``ts`` becomes a timestamp so it can be watermarked."""
    stream = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return what it wrote."""
    spark = stream.sparkSession
    out, marks = new_path(spark, "stream-out"), new_path(spark, "stream-marks")
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", marks).outputMode(mode).trigger(availableNow=True).start()
    else:
        last = lambda batch, _: batch.write.mode("overwrite").parquet(out)
        query = stream.writeStream.foreachBatch(last).option("checkpointLocation", marks).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width)).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").alias("start"), "n", "total")


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def all_windows_closed(stream: DataFrame, make, watermark: str = "1 hour") -> DataFrame:
    """Drain a windowed stream in complete mode, so that windows still open at the end are there too."""
    return drain(make(stream.withWatermark("ts", watermark)), "complete")


def deduplicated(stream: DataFrame, *keys: str, watermark: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(list(keys))


def with_users(stream: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: each event with its user's customer row."""
    return stream.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


def interval_pairs(left: DataFrame, right: DataFrame, minutes: int) -> DataFrame:
    """Pairs of one user: an event on the right at most ``minutes`` after one on the left."""
    a = left.select("user_id", F.col("event_id").alias("first"), F.col("ts").alias("ta"))
    b = right.select(F.col("user_id").alias("user_b"), F.col("event_id").alias("second"), F.col("ts").alias("tb"))
    if left.isStreaming:
        a, b = a.withWatermark("ta", "1 hour"), b.withWatermark("tb", "1 hour")
    near = F.expr(f"user_id = user_b AND tb > ta AND tb <= ta + interval {minutes} minutes")
    return a.join(b, near).select("user_id", "first", "second")
