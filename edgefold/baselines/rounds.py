"""Comparators outside the vertex model: map/reduce rounds, sparse matrix products, and an RDD program."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..proxy.graph import ProxyGraph
from ..runtime.scratch import drop, save

UNIT = 1_000_000_000


def mapreduce_pagerank(g: PropertyGraph, iterations: int) -> DataFrame:
    """Scaled ranks by rounds that read and write the whole graph, ranks and adjacency lists together."""
    lists = g.edges.groupBy(F.col("src").alias("id")).agg(F.collect_list("dst").alias("targets"))
    nodes = save(g.vertices.select("id").join(lists, "id", "left").select("id", F.lit(UNIT).cast("long").alias("rank"), F.coalesce("targets", F.array().cast("array<bigint>")).alias("targets")), "round")
    for _ in range(iterations):
        shares = nodes.select(F.explode("targets").alias("id"), F.expr("rank div size(targets)").alias("share"), F.lit(None).cast("array<bigint>").alias("targets"))
        same = nodes.select("id", F.lit(0).cast("long").alias("share"), "targets")
        reduced = shares.unionByName(same).groupBy("id").agg(F.sum("share").alias("acc"), F.first("targets", ignorenulls=True).alias("targets"))
        after = save(reduced.select("id", F.expr("150000000L + (85 * acc) div 100").alias("rank"), "targets"), "round")
        drop(g.spark, nodes)
        nodes = after
    return nodes.select("id", F.col("rank").alias("result"))


#: Semirings: (how an entry meets a vector value, how products add up).
SEMIRINGS = {
    "plus_times": (lambda val, x: val * x, F.sum),
    "min_plus": (lambda val, x: val + x, F.min),
    "min_first": (lambda val, x: x, F.min),
}


def spmv(matrix: DataFrame, x: DataFrame, semiring: str = "plus_times") -> DataFrame:
    """(row, y): product of (row, col, val) with (col, x) over a semiring; absent entries are its zero."""
    meet, add = SEMIRINGS[semiring]
    return matrix.join(x, "col").groupBy("row").agg(add(meet(F.col("val"), F.col("x"))).alias("y"))


def spmv_pagerank(g: PropertyGraph, iterations: int) -> DataFrame:
    """Scaled ranks as repeated matrix products; whole division keeps every order of addition exact."""
    degrees = g.out_degrees().select(F.col("id").alias("src"), "out_degree")
    matrix = g.edges.join(degrees, "src").select(F.col("dst").alias("row"), F.col("src").alias("col"), F.lit(1).cast("long").alias("val"), "out_degree").persist()
    x = save(g.vertices.select(F.col("id").alias("col"), F.lit(UNIT).cast("long").alias("x")), "vector")
    share = g.vertices.select(F.col("id").alias("col")).join(degrees.withColumnRenamed("src", "col"), "col")
    for _ in range(iterations):
        split = x.join(share, "col").select("col", F.expr("x div out_degree").alias("x"))
        y = spmv(matrix, split)
        after = save(g.vertices.select(F.col("id").alias("row")).join(y, "row", "left").select(F.col("row").alias("col"), F.expr("150000000L + (85 * coalesce(y, 0L)) div 100").alias("x")), "vector")
        drop(g.spark, x)
        x = after
    matrix.unpersist()
    return x.select(F.col("col").alias("id"), F.col("x").alias("result"))


def rdd_pagerank(g: PropertyGraph, iterations: int) -> DataFrame:
    """Scaled ranks by a plain RDD program, the live stand-in for quoted third-party times."""
    spark = g.spark
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    links = g.edges.select("src", "dst").rdd.map(lambda r: (r[0], r[1])).groupByKey(n).mapValues(list).persist()
    vertices = g.vertices.select("id").rdd.map(lambda r: (r[0], 0)).partitionBy(n).persist()
    ranks = vertices.mapValues(lambda _: UNIT)
    for _ in range(iterations):
        sent = links.join(ranks, n).flatMap(lambda kv: [(t, kv[1][1] // len(kv[1][0])) for t in kv[1][0]])
        ranks = vertices.leftOuterJoin(sent.reduceByKey(lambda a, b: a + b, n), n).mapValues(lambda v: 150_000_000 + 85 * (v[1] or 0) // 100)
    return spark.createDataFrame(ranks, "id long, result long")


def engine_axes(pg: ProxyGraph) -> DataFrame:
    """(engine, data_model, computation_model, communication_model, rows_moved) of every engine here.

    ``rows_moved`` is what the communication model moves or stores in a step in which all vertices of the placed graph emit.
    """
    rows = [
        ("one-sided flat", "edges by source", "one-sided messages", "merged messages", "targets"),
        ("one-sided proxied", "proxy graph", "one-sided messages", "one direction per proxy", "proxies"),
        ("gather-apply-scatter", "edges with state", "split phases", "shared edge values", "edges"),
        ("mirror", "vertex-cut with mirrors", "split phases", "collect and broadcast", "mirrors both ways"),
        ("message super-steps", "edges by source", "vertex programs", "stored messages", "edges"),
        ("map/reduce rounds", "adjacency records", "map and reduce", "whole graph each round", "edges and vertices"),
        ("matrix products", "sparse matrix", "semiring products", "vector shuffles", "vertices"),
        ("rdd", "partitioned pairs", "joins and reductions", "merged pairs", "targets"),
    ]
    axes = ["engine", "data_model", "computation_model", "communication_model"]
    named = pg.edges.sparkSession.createDataFrame(rows, ", ".join(f"{c} string" for c in [*axes, "moved"]))
    counts = pg.edges.agg(F.count("*").alias("e"), F.countDistinct("dst").alias("t")).crossJoin(pg.homes.agg(F.count("*").alias("v")))
    counts = counts.crossJoin(pg.proxies.agg(F.count("*").alias("p"), F.countDistinct("pid", "id").alias("m")))
    kinds = {"targets": F.col("t"), "proxies": F.col("p"), "edges": F.col("e"), "mirrors both ways": 2 * F.col("m"), "edges and vertices": F.col("e") + F.col("v"), "vertices": F.col("v")}
    moved = F.coalesce(*(F.when(F.col("moved") == kind, n) for kind, n in kinds.items()))
    return named.crossJoin(counts).select(*axes, moved.alias("rows_moved"))
