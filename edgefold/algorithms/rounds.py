"""Round-based algorithms over undirected views: spanning forest, colouring, weighted matching."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..runtime.scratch import drop, save
from .contract import contract_components


def spanning_forest(g: PropertyGraph, weight: str = "w", max_rounds: int = 100) -> DataFrame:
    """(src, dst, w): a minimum spanning forest of the undirected view; ties go to smaller (src, dst).

    Every component takes its lightest outgoing edge, and components so joined contract; the number of
    components at least halves per round.
    """
    edges = g.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), F.col(weight).alias("w")).where("src <> dst")
    edges = save(edges.groupBy("src", "dst").agg(F.min("w").alias("w")), "light")
    live, chosen, labels = edges.withColumns({"a": F.col("src"), "b": F.col("dst")}), None, None
    live = save(live, "live")
    for _ in range(max_rounds):
        if live.limit(1).count() == 0:
            break
        best = F.min(F.struct("w", "src", "dst")).alias("e")
        ends = live.select(F.col("a").alias("c"), "w", "src", "dst").unionByName(live.select(F.col("b").alias("c"), "w", "src", "dst"))
        picked = ends.groupBy("c").agg(best).select("e.src", "e.dst", "e.w").distinct()
        chosen = save(picked if chosen is None else chosen.unionByName(picked), "forest")
        labels = save(contract_components(chosen), "labels")
        named = lambda end, to: labels.select(F.col("id").alias(end), F.col("label").alias(to))
        moved = edges.join(named("src", "a"), "src", "left").join(named("dst", "b"), "dst", "left")
        after = save(moved.withColumns({"a": F.coalesce("a", "src"), "b": F.coalesce("b", "dst")}).where("a <> b"), "live")
        drop(g.spark, live)
        live = after
    return chosen if chosen is not None else edges


def colouring(g: PropertyGraph, seed: int = 7, max_rounds: int = 1000) -> DataFrame:
    """(id, colour): neighbours differ. A round colours the vertices whose scrambled priority beats all uncoloured neighbours'."""
    edges = save(g.symmetrize().edges, "around")
    left, done, r = save(g.vertices.select("id"), "left"), [], 0
    for r in range(max_rounds):
        if left.limit(1).count() == 0:
            break
        rank = F.struct(F.xxhash64(F.lit(seed), F.lit(r), "id").alias("p"), "id")
        ranked = left.select("id", rank.alias("rank"))
        beaten = edges.join(ranked.select(F.col("id").alias("src"), F.col("rank").alias("rs")), "src").join(ranked.select(F.col("id").alias("dst"), F.col("rank").alias("rd")), "dst").where("rs > rd").select(F.col("dst").alias("id")).distinct()
        winners = save(left.join(beaten, "id", "left_anti"), "winners")
        done.append(winners.withColumn("colour", F.lit(r)))
        after = save(left.join(winners, "id", "left_anti"), "left")
        drop(g.spark, left)
        left = after
    out = g.vertices.select("id", F.lit(0).alias("colour")).limit(0)
    for d in done:
        out = out.unionByName(d)
    return out


def weighted_matching(g: PropertyGraph, weight: str = "w", max_rounds: int = 1000) -> DataFrame:
    """(src, dst, w): a matching of at least half the largest weight; edges that are heaviest at both ends match."""
    plain = g.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), F.col(weight).alias("w")).where("src <> dst")
    live, done = save(plain.groupBy("src", "dst").agg(F.max("w").alias("w")), "live"), []
    for _ in range(max_rounds):
        if live.limit(1).count() == 0:
            break
        both = live.select(F.col("src").alias("v"), "src", "dst", "w").unionByName(live.select(F.col("dst").alias("v"), "src", "dst", "w"))
        picks = both.groupBy("v").agg(F.max(F.struct("w", F.negative("src").alias("x"), F.negative("dst").alias("y"))).alias("e"))
        mutual = picks.select((-F.col("e.x")).alias("src"), (-F.col("e.y")).alias("dst"), F.col("e.w").alias("w")).groupBy("src", "dst", "w").count().where("count = 2").drop("count")
        matched = save(mutual, "matched")
        done.append(matched)
        ends = matched.select(F.col("src").alias("v")).unionByName(matched.select(F.col("dst").alias("v")))
        after = save(live.join(ends.withColumnRenamed("v", "src"), "src", "left_anti").join(ends.withColumnRenamed("v", "dst"), "dst", "left_anti").select("src", "dst", "w"), "live")
        drop(g.spark, live)
        live = after
    out = live.limit(0)
    for d in done:
        out = out.unionByName(d)
    return out
