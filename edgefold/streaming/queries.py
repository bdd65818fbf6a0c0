"""Registered streaming queries; each drains the file stream, and its SQL twin reads the table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import build
from ..graph.build import table
from ..oracles.graphs import ctes, greedy, labels
from ..runtime.scratch import new_path
from . import events as ev
from .graphs import GrowingComponents, PlacedStream


def _edge_stream(spark: SparkSession, sf: str, graph: str, files: int = 4) -> DataFrame:
    path = new_path(spark, "edge-files")
    build.GRAPHS[graph](spark, sf).edges.select("src", "dst").repartition(files, "src").write.parquet(path)
    return spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 2).parquet(path)


def stream_edges_count(spark: SparkSession, sf: str) -> DataFrame:
    counted = ev.read_stream(spark, sf).groupBy("event_type").agg(F.count("*").alias("n"))
    return ev.drain(counted, "complete")


def stream_tumbling(spark: SparkSession, sf: str) -> DataFrame:
    return ev.all_windows_closed(ev.read_stream(spark, sf), ev.tumbling).select(F.unix_seconds("start").alias("start_s"), "n", "total")


def stream_sliding(spark: SparkSession, sf: str) -> DataFrame:
    return ev.all_windows_closed(ev.read_stream(spark, sf), ev.sliding).select(F.unix_seconds("start").alias("start_s"), "event_type", "n")


def stream_session(spark: SparkSession, sf: str) -> DataFrame:
    return ev.all_windows_closed(ev.read_stream(spark, sf), ev.sessions).select("user_id", F.unix_micros("start").alias("start_us"), "n")


def stream_dedup(spark: SparkSession, sf: str) -> DataFrame:
    return ev.drain(ev.deduplicated(ev.read_stream(spark, sf), "event_id").select("event_id", "user_id"))


def stream_static_join(spark: SparkSession, sf: str) -> DataFrame:
    joined = ev.with_users(ev.read_stream(spark, sf), table(spark, sf, "customer"))
    return ev.drain(joined.select("event_id", "c_mktsegment"))


def stream_interval_join(spark: SparkSession, sf: str) -> DataFrame:
    clicks = ev.read_stream(spark, sf).where("event_type = 'click'")
    bought = ev.read_stream(spark, sf).where("event_type = 'purchase'")
    return ev.drain(ev.interval_pairs(clicks, bought, 120))


def stream_greedy_place(spark: SparkSession, sf: str) -> DataFrame:
    return PlacedStream(4).follow(_edge_stream(spark, sf, "trade"))


def stream_greedy_place_serial(spark: SparkSession, sf: str) -> DataFrame:
    """One loader that gets the stream as one batch places as the serial loader of a list sorted by source."""
    return PlacedStream(4, loaders=1).follow(_edge_stream(spark, sf, "trade", files=1)).select("src", "dst", "pid")


def stream_components(spark: SparkSession, sf: str) -> DataFrame:
    return GrowingComponents().follow(_edge_stream(spark, sf, "sharedline")).select("id", "label")


QUERIES = {
    "stream_edges_count": (stream_edges_count, "SELECT event_type, count(*) AS n FROM events GROUP BY 1"),
    "stream_tumbling": (stream_tumbling, "SELECT epoch(date_trunc('day', ts))::BIGINT AS start_s, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1"),
    "stream_sliding": (stream_sliding, "SELECT (epoch(date_trunc('day', ts))::BIGINT - 86400 * k) AS start_s, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY 1, 2"),
    "stream_session": (
        stream_session,
        "WITH g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 7200000000 THEN 0 ELSE 1 END AS f FROM events), n AS (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g) SELECT user_id, min(epoch_us(ts)) AS start_us, count(*) AS n FROM n GROUP BY user_id, s",
    ),
    "stream_dedup": (stream_dedup, "SELECT event_id, user_id FROM events"),
    "stream_static_join": (stream_static_join, "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id"),
    "stream_interval_join": (
        stream_interval_join,
        "SELECT a.user_id, a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 120 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
    ),
    "stream_greedy_place": (stream_greedy_place, None),
    "stream_greedy_place_serial": (stream_greedy_place_serial, f"WITH RECURSIVE {ctes('trade')},\n{greedy('e', 'src, dst', 4)}\nSELECT src, dst, pid FROM g WHERE edge_seq >= 0"),
    "stream_components": (stream_components, labels("sharedline")),
}
