"""Placements that look at one key only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph.ids import mix


def hash_homes(vertices: DataFrame, k: int, arithmetic: bool = True) -> DataFrame:
    """(id, home): random vertex sharding, by the arithmetic scramble (same in SQL) or a 64-bit hash."""
    home = mix("id") % k if arithmetic else F.pmod(F.xxhash64("id"), F.lit(k))
    return vertices.select("id", home.cast("int").alias("home"))


def apart(k: int) -> Column:
    """Whether an edge's ends have different homes under the arithmetic scramble."""
    return mix("src") % k != mix("dst") % k


def edge_hash_place(edges: DataFrame, k: int) -> DataFrame:
    """(src, dst, pid): vertex-cut by a scramble of both ends, without any heuristic."""
    return edges.select("src", "dst", ((mix("src") * 31 + mix("dst")) % 1000003 % k).cast("int").alias("pid"))


def place_edges(edges: DataFrame, homes: DataFrame, rule: str = "at_source") -> DataFrame:
    """(src, dst, pid) from vertex homes.

    ``at_source`` keeps an edge with its source, so in-proxies stand for remote targets; ``at_target``
    moves it to its target, so out-proxies stand for remote sources; ``min_proxy`` takes, for every
    ordered pair of parts, the side that needs fewer proxies for the edges between them.
    """
    at = edges.select("src", "dst").join(homes.select(F.col("id").alias("src"), F.col("home").alias("hs")), "src").join(homes.select(F.col("id").alias("dst"), F.col("home").alias("hd")), "dst")
    if rule == "at_source":
        return at.select("src", "dst", F.col("hs").alias("pid"))
    if rule == "at_target":
        return at.select("src", "dst", F.col("hd").alias("pid"))
    if rule == "min_proxy":
        pairs = at.groupBy("hs", "hd").agg(F.countDistinct("src").alias("ns"), F.countDistinct("dst").alias("nd"))
        chosen = pairs.select("hs", "hd", F.when(F.col("ns") < F.col("nd"), F.col("hd")).otherwise(F.col("hs")).alias("pid"))
        return at.join(chosen, ["hs", "hd"]).select("src", "dst", "pid")
    raise ValueError(f"unknown rule {rule}")
