"""Orders in which loaders read an edge list. Greedy placement depends on the order, so it is explicit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..graph.ids import mix


def sort_keys(edges: DataFrame, order: str) -> tuple[DataFrame, list]:
    """The edges with what an order needs, and its sort keys; (src, dst) always breaks ties."""
    if order == "source":
        return edges, ["src", "dst"]
    if order == "mixed":
        return edges, [(mix("src") * 31 + mix("dst")) % 1000003, "src", "dst"]
    if order == "digest":
        return edges, [F.md5(F.concat_ws(":", "src", "dst")), "src", "dst"]
    if order == "degree":
        out = edges.groupBy("src").agg(F.count("*").alias("_do"))
        into = edges.groupBy("dst").agg(F.count("*").alias("_di"))
        return edges.join(out, "src").join(into, "dst"), [F.desc(F.col("_do") + F.col("_di")), "src", "dst"]
    raise ValueError(f"unknown order {order}")


def loader_of(loaders: int) -> Column:
    """The loader that an edge is dealt to, by a scramble of its ends; ids below 0 have one too."""
    return F.pmod((mix("dst") * 17 + mix("src")) % 1000003, F.lit(loaders)).cast("int")


def order_edges(edges: DataFrame, order: str = "mixed", loaders: int = 1) -> DataFrame:
    """(edge_seq, src, dst, loader): loaders take edges by a scramble of their ends and number their own.

    ``edge_seq`` is per loader; with one loader it numbers the whole list, which only small graphs allow.
    """
    known, keys = sort_keys(edges.select("src", "dst"), order)
    dealt = known.withColumn("loader", loader_of(loaders))
    here = Window.partitionBy("loader").orderBy(*keys)
    return dealt.select((F.row_number().over(here) - 1).cast("long").alias("edge_seq"), "src", "dst", "loader")
