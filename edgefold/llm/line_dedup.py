"""Line dedup by site-relative frequency.

For every host, the pages that hold a line are divided by the host's pages; a line held by at least
``min_pages`` pages and by more than ``max_percent`` of them is boilerplate of that host and is dropped
from its pages. Lines are compared trimmed, by 64-bit hash; blank lines are never dropped.

Only (host, line hash) counts are shuffled, after partial counting in the map tasks, so a line that
every page holds is one row per task. The boilerplate of one host has at most
100 * (lines per page) / max_percent members, whatever the host's size, because each takes up that
share of its pages. They are laid out as a hash table, an array of about as many slots as lines, so that a line
costs one slot's few comparisons. The tables are broadcast if their checked total is small and joined by host
otherwise, where a hot host's pages may be split over tasks.

Cases: a null host is a host of its own; null texts have no lines and stay null; repeated rows are
pages of their own; empty tables give empty results; other columns are carried along untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime.scratch import save

#: Most boilerplate lines (16 bytes each) that are broadcast.
BROADCAST_LINES = 500_000
EDGE = " \t\r"


def line_key(line: Column) -> Column:
    return F.xxhash64(F.btrim(line, F.lit(EDGE)))


def boilerplate(docs: DataFrame, host_col: str = "source", text_col: str = "text", max_percent: int = 5, min_pages: int = 5) -> DataFrame:
    """(host, line): the hash of each host's boilerplate lines."""
    pages = docs.select(F.coalesce(F.col(host_col).cast("string"), F.lit("\0")).alias("host"), F.col(text_col).cast("string").alias("text"))
    full = F.filter(F.split("text", "\n"), lambda x: F.btrim(x, F.lit(EDGE)) != "")
    lines = pages.select("host", F.explode(F.array_distinct(F.transform(full, line_key))).alias("line"))
    counts = lines.groupBy("host", "line").agg(F.count("*").alias("pages")).where(F.col("pages") >= min_pages)
    totals = pages.groupBy("host").agg(F.count("*").alias("total"))
    return counts.join(totals, "host").where(100 * F.col("pages") > max_percent * F.col("total")).select("host", "line")


def slots(lines: DataFrame) -> DataFrame:
    """(host, slots): an array of arrays; a line is in slot ``line mod size``, and the size is a power of two."""
    sizes = lines.groupBy("host").agg(F.pow(F.lit(2), F.ceil(F.log2(F.count("*")))).cast("long").alias("size"))
    held = lines.join(sizes, "host").groupBy("host", F.pmod("line", "size").alias("slot")).agg(F.collect_set("line").alias("lines"))
    every = sizes.select("host", F.explode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1)).alias("slot"))
    full = every.join(held, ["host", "slot"], "left").groupBy("host").agg(F.array_sort(F.collect_list(F.struct("slot", F.coalesce("lines", F.array().cast("array<bigint>")).alias("lines")))).alias("all"))
    return full.select("host", F.transform("all", lambda x: x["lines"]).alias("slots"))


def dedup_lines(docs: DataFrame, host_col: str = "source", text_col: str = "text", max_percent: int = 5, min_pages: int = 5) -> DataFrame:
    """(row, text, n_lines, n_dropped): the input row as a struct, its text without boilerplate, line counts."""
    lines = save(boilerplate(docs, host_col, text_col, max_percent, min_pages), "boilerplate")
    found, size = slots(lines), lines.count()
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.coalesce(F.col(host_col).cast("string"), F.lit("\0")).alias("host"), F.col(text_col).cast("string").alias("_text"))
    joined = rows.join(F.broadcast(found) if size <= BROADCAST_LINES else found, "host", "left")
    every = F.split("_text", "\n")
    kept = F.filter(every, lambda x: ~F.array_contains(F.get("slots", F.pmod(line_key(x), F.size("slots"))), line_key(x)))
    text = F.when(F.col("slots").isNull(), F.col("_text")).otherwise(F.array_join(kept, "\n"))
    n_lines = F.coalesce(F.size(every), F.lit(0))
    n_kept = F.when(F.col("slots").isNull(), n_lines).otherwise(F.coalesce(F.size(kept), F.lit(0)))
    has_text = F.col("_text").isNotNull()
    return joined.select(
        "row",
        F.when(has_text, text).alias("text"),
        F.when(has_text, n_lines).otherwise(0).cast("long").alias("n_lines"),
        F.when(has_text, n_lines - n_kept).otherwise(0).cast("long").alias("n_dropped"),
    )


def oracle(max_percent: int = 5, min_pages: int = 5) -> str:
    """DuckDB SQL for the digest of :func:`dedup_lines` over ``documents``."""
    return rf"""
WITH p AS (SELECT row_number() OVER () AS r, doc_id, coalesce(source, chr(0)) AS host, text FROM documents),
l AS (SELECT r, doc_id, host, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS k FROM p WHERE text IS NOT NULL),
n AS (SELECT host, trim(line, ' ' || chr(9) || chr(13)) AS t, count(DISTINCT r) AS pages FROM l GROUP BY ALL),
h AS (SELECT host, count(*) AS total FROM p GROUP BY host),
b AS (SELECT host, t FROM n JOIN h USING (host) WHERE t <> '' AND pages >= {min_pages} AND 100 * pages > {max_percent} * total),
k AS (SELECT l.*, b.t IS NOT NULL AS gone FROM l LEFT JOIN b ON l.host = b.host AND trim(l.line, ' ' || chr(9) || chr(13)) = b.t),
g AS (SELECT r, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped, coalesce(string_agg(line, chr(10) ORDER BY k) FILTER (NOT gone), '') AS text FROM k GROUP BY r)
SELECT p.doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_dropped, 0)::BIGINT AS n_dropped,
  length(coalesce(g.text, ''))::BIGINT AS n_chars, sha256(coalesce(g.text, '')) AS text_sha256 FROM p LEFT JOIN g USING (r)
"""
