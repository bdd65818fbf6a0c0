"""Graphs from the given tables; each stands for a family of the reference's inputs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..runtime.scratch import save
from .ids import text_key, typed
from .model import PropertyGraph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _counted(pairs: DataFrame) -> PropertyGraph:
    return PropertyGraph.from_edges(pairs.groupBy("src", "dst").agg(F.count("*").alias("w")))


def handoff(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """User of an event to user of the next one; w counts, loops dropped.

    The order is global. Days are numbered first and each is ordered in its own task; only the first
    event of a day needs the last one of the day before, which is one row per day.
    """
    events = table(spark, sf_dir, "events").select("event_id", "ts", F.col("user_id").cast("long").alias("u")).withColumn("day", F.to_date("ts"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    steps = events.select("day", "u", F.lead("u").over(inside).alias("v"))
    key = F.struct("ts", "event_id", "u")
    days = events.groupBy("day").agg(F.min(key).alias("first"), F.max(key).alias("last"))
    seams = days.select(F.col("last.u").alias("src"), F.lead("first.u").over(Window.orderBy("day")).alias("dst"))
    pairs = steps.select(F.col("u").alias("src"), F.col("v").alias("dst")).where("dst IS NOT NULL").unionByName(seams.where("dst IS NOT NULL"))
    return _counted(pairs.where("src <> dst"))


def handoff_strong(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return PropertyGraph.from_edges(handoff(spark, sf_dir).edges.where("w >= 3"))


def purchase(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Customer to supplier of an ordered line; many-to-few, so heavy in-degree."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    return _counted(pairs.select(typed("o_custkey", "customer").alias("src"), typed("l_suppkey", "supplier").alias("dst")))


def purchase_rev(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return purchase(spark, sf_dir).transpose()


def trade(spark: SparkSession, sf_dir: str, bought: PropertyGraph | None = None) -> PropertyGraph:
    """Nation of the customer to nation of the supplier, loops dropped; ``bought`` is :func:`purchase`, if it is there already."""
    pairs = (bought or purchase(spark, sf_dir)).edges.select(F.expr("src div 16").alias("c"), F.expr("dst div 16").alias("s"), "w")
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("c"), F.col("c_nationkey").cast("long").alias("src"))
    suppliers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("s"), F.col("s_nationkey").cast("long").alias("dst"))
    named = pairs.join(customers, "c").join(suppliers, "s").where("src <> dst")
    return PropertyGraph.from_edges(named.groupBy("src", "dst").agg(F.sum("w").alias("w")))


def hyperlink(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Page to the paths it links to."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1)))).alias("path"))
    edges = pages.select(typed("page_id", "page").alias("src"), typed(text_key(F.col("path")), "path").alias("dst")).distinct()
    return PropertyGraph.from_edges(edges)


def sharedline(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Document to each of its lines of more than 20 characters that another document has too."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    lines = docs.select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where(F.length("line") > 20)
    pairs = lines.select(typed("doc_id", "document").alias("src"), typed(text_key(F.col("line")), "line").alias("dst")).distinct()
    several = pairs.groupBy("dst").agg(F.count("*").alias("n")).where("n >= 2").select("dst")
    return PropertyGraph.from_edges(pairs.join(several, "dst", "left_semi").select("src", "dst"))


def thread(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Turn to next turn of a conversation; single turns are lone vertices."""
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    here = Window.partitionBy("conv_id").orderBy("turn")
    stepped = turns.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), (F.col("conv_id") * 1000 + F.lead("turn").over(here)).alias("next"))
    edges = stepped.where("next IS NOT NULL").select(F.col("id").alias("src"), F.col("next").alias("dst"), F.lit(1).cast("long").alias("w"))
    return PropertyGraph(stepped.select("id").distinct(), edges)


def part_supplier(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    lines = table(spark, sf_dir, "lineitem")
    return PropertyGraph.from_edges(lines.select(typed("l_partkey", "part").alias("src"), typed("l_suppkey", "supplier").alias("dst")).distinct())


def copurchase(spark: SparkSession, sf_dir: str, least: int = 1) -> PropertyGraph:
    """Parts of one order, a < b, with w a fixed scramble of the pair; undirected by convention."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("p"))
    lines = lines.distinct()
    pairs = lines.withColumnRenamed("p", "src").join(lines.withColumnRenamed("p", "dst"), "l_orderkey").where("src < dst")
    counted = pairs.groupBy("src", "dst").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    return PropertyGraph.from_edges(counted.select("src", "dst", (1 + (F.col("src") * 7919 + F.col("dst") * 104729) % 1000003).alias("w")))


def knn(spark: SparkSession, sf_dir: str, k: int = 16, block: int = 512, chunk: int = 16_384) -> PropertyGraph:
    """Vector to its ``k`` nearest by cosine (ties to the smaller id), by blocks of a bounded matrix product.

    Chunks of about ``chunk`` vectors are broadcast one after the other; the best of every chunk are written,
    and the best of these are the neighbours, so any number of vectors is compared exactly.
    """
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    n_chunks = max(1, -(-rows.count() // chunk))
    found = None
    for c in range(n_chunks):
        whole = rows.where(F.pmod(F.xxhash64("id"), F.lit(n_chunks)) == c).orderBy("id").toPandas()
        if whole.empty:
            continue
        ids, vectors = whole["id"].to_numpy(), np.stack(whole["embedding"].to_list()).astype(np.float64)
        shared = spark.sparkContext.broadcast((ids, vectors / np.linalg.norm(vectors, axis=1, keepdims=True)))

        def near(frames, shared=shared):
            ids, vectors = shared.value
            for frame in frames:
                for a in range(0, len(frame), block):
                    part = frame.iloc[a : a + block]
                    own = np.stack(part["embedding"].to_list()).astype(np.float64)
                    score = np.nan_to_num(np.round((own / np.linalg.norm(own, axis=1, keepdims=True)) @ vectors.T, 9), nan=-2.0)
                    score[part["id"].to_numpy()[:, None] == ids[None, :]] = -np.inf
                    best = np.argsort(-score, axis=1, kind="stable")[:, :k]
                    made = pd.DataFrame({"src": np.repeat(part["id"].to_numpy(), best.shape[1]), "dst": ids[best].ravel(), "score": np.take_along_axis(score, best, axis=1).ravel()})
                    yield made[made["score"] > -np.inf]

        best = rows.mapInPandas(near, "src long, dst long, score double")
        if n_chunks > 1:
            best = save(best, "near")
            shared.destroy()
        found = best if found is None else found.unionByName(best)
    if found is None:
        return PropertyGraph.from_edges(spark.createDataFrame([], "src long, dst long"))
    if n_chunks > 1:
        order = Window.partitionBy("src").orderBy(F.desc("score"), "dst")
        found = found.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= k)
    return PropertyGraph.from_edges(found.select("src", "dst"))


def with_random_weights(g: PropertyGraph, low: int = 1, high: int = 100) -> PropertyGraph:
    """Edges with whole weights in [low, high], a fixed scramble of their ends that stays in 64 bits for any ids."""
    scramble = F.col("src") % 1000003 * 7919 + F.col("dst") % 1000003 * 104729
    w = low + F.pmod(scramble, F.lit(1000003)) % (high - low + 1)
    return PropertyGraph(g.vertices, g.edges.withColumn("w", w))


GRAPHS = {"handoff": handoff, "purchase": purchase, "purchase_rev": purchase_rev, "trade": trade, "hyperlink": hyperlink, "sharedline": sharedline, "thread": thread}
