"""Recursive-matrix graphs: 2^scale vertices, each edge drawn by one quadrant choice per bit.

Choices come from digits of a digest of (seed, edge, level), so any SQL engine can draw the same graph,
partitions don't matter, and a lost task draws the same edges again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import PropertyGraph

#: Shares of the four quadrants in hundredths (a, b, c, d).
QUADRANTS = (57, 19, 19, 5)


def rmat_edges(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 1) -> DataFrame:
    """(edge_seq, src, dst) of 2^scale * edge_factor raw edges, loops and repeats included."""
    return drawn(spark.range((1 << scale) * edge_factor).withColumnRenamed("id", "edge_seq"), scale, seed)


def drawn(edges: DataFrame, scale: int, seed: int = 1) -> DataFrame:
    """(edge_seq, src, dst): the raw edge of every row's ``edge_seq``."""
    a, b, c, _ = QUADRANTS
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    # eight hex digits decide one level, so a digest of 32 serves four
    for group in range((scale + 3) // 4):
        edges = edges.withColumn(f"_d{group}", F.md5(F.concat(F.lit(f"{seed}:"), F.col("edge_seq"), F.lit(f":{group}"))))
    for level in range(scale):
        draw = F.conv(F.substring(f"_d{level // 4}", 1 + 8 * (level % 4), 8), 16, 10).cast("long") % 100
        src = src * 2 + (draw >= a + b).cast("long")
        dst = dst * 2 + (((draw >= a) & (draw < a + b)) | (draw >= a + b + c)).cast("long")
    return edges.select("edge_seq", src.alias("src"), dst.alias("dst"))


def rmat(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 1, dedup: bool = False, drop_loops: bool = False, permute: bool = False) -> PropertyGraph:
    """Graph of :func:`rmat_edges`; vertices are all of 0..2^scale - 1. ``permute`` relabels by an odd multiplier."""
    edges = rmat_edges(spark, scale, edge_factor, seed).select("src", "dst")
    if permute:
        n = 1 << scale
        edges = edges.select(*(((F.col(c) * 2654435761 + 12345) % n).alias(c) for c in ("src", "dst")))
    if drop_loops:
        edges = edges.where("src <> dst")
    return PropertyGraph(spark.range(1 << scale), edges.distinct() if dedup else edges)


def rmat_sql(scale: int, edge_factor: int = 16, seed: int = 1, numbers: str | None = None) -> str:
    """DuckDB SQL of (edge_seq, src, dst), for the edge numbers i of ``numbers`` or 2^scale * edge_factor of them."""
    a, b, c, _ = QUADRANTS
    draw = lambda l: f"(('0x' || substr(md5('{seed}:' || i || ':{l // 4}'), {1 + 8 * (l % 4)}, 8))::BIGINT % 100)"  # noqa: E731, E741
    draws = ", ".join(f"{draw(n)} AS d{n}" for n in range(scale))
    src = " + ".join(f"(d{n} >= {a + b})::BIGINT * {1 << (scale - 1 - n)}" for n in range(scale))
    dst = " + ".join(f"((d{n} >= {a} AND d{n} < {a + b}) OR d{n} >= {a + b + c})::BIGINT * {1 << (scale - 1 - n)}" for n in range(scale))
    return f"SELECT i AS edge_seq, {src} AS src, {dst} AS dst FROM (SELECT i, {draws} FROM {numbers or f'range({(1 << scale) * edge_factor}) t(i)'})"
