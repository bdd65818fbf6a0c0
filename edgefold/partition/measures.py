"""Cost measures of placements; every one is a small aggregate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..proxy.graph import ProxyGraph


def _count(df: DataFrame, name: str, rule: str | None = None) -> DataFrame:
    return (df.where(rule) if rule else df).agg(F.count("*").alias(name))


def proxy_measures(pg: ProxyGraph, k: int) -> DataFrame:
    """One row: k, v, e, s, c, replicas, max_load and the rates that follow from them."""
    roles = pg.proxies.agg(F.count_if(F.col("role") == "out").alias("s"), F.count_if(F.col("role") == "in").alias("c"), F.countDistinct("pid", "id").alias("m"))
    loads = pg.edges.groupBy("pid").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("e"), F.coalesce(F.max("n"), F.lit(0)).alias("max_load"))
    row = _count(pg.homes, "v").crossJoin(loads).crossJoin(roles)
    proxies, v = F.col("s") + F.col("c"), F.col("v")
    return row.select(
        F.lit(k).alias("k"),
        "v",
        "e",
        "s",
        "c",
        (v + F.col("m")).alias("replicas"),
        "max_load",
        (proxies / v).alias("proxy_rate"),
        (proxies / F.col("e")).alias("equivalent_cut"),
        (proxies / v).alias("cut_factor"),
        (2 * F.col("m") / v).alias("mirror_cut_factor"),
        ((v + F.col("m")) / v).alias("replication"),
        (F.col("max_load") * k / F.col("e")).alias("balance"),
    )


#: Tasks that sum up the counts of placements; many small ones need not spill.
SUMMED = 128


def placements(present: DataFrame) -> DataFrame:
    """(graph, way, ends, e, s, c, m) of many placements (graph, way, id, pid, out, into) at once; ``ends`` counts vertices with an edge.

    The counts are those of :func:`proxy_measures` with homes at the part that has most of a vertex's edges.
    """
    here, key = ["graph", "way"], F.struct(F.col("out") + F.col("into"), -F.col("pid"))
    whole = present.repartition(SUMMED, *here, "id").groupBy(*here, "id", "pid").agg(F.sum("out").alias("out"), F.sum("into").alias("into"))
    at_home = F.max_by(F.struct((F.col("out") > 0).cast("long").alias("o"), (F.col("into") > 0).cast("long").alias("i")), key)
    spread = whole.groupBy(*here, "id").agg(F.count("*").alias("parts"), F.sum("out").alias("edges"), F.count_if(F.col("out") > 0).alias("o"), F.count_if(F.col("into") > 0).alias("i"), at_home.alias("home"))
    sums = {"e": F.col("edges"), "s": F.col("o") - F.col("home.o"), "c": F.col("i") - F.col("home.i"), "m": F.col("parts") - 1}
    return spread.groupBy(*here).agg(F.count("*").alias("ends"), *(F.sum(x).alias(n) for n, x in sums.items()))


def objective(pg: ProxyGraph, k: int, eps: float = 0.1) -> DataFrame:
    """(avg_proxies, max_load, feasible): what balanced k-way placement minimises, and its bound."""
    m = proxy_measures(pg, k)
    return m.select(((F.col("s") + F.col("c")) / k).alias("avg_proxies"), "max_load", (F.col("max_load") < (1 + eps) * F.col("e") / k).alias("feasible"))


def edge_cut(edges: DataFrame, homes: DataFrame) -> DataFrame:
    """(cut, rate): edges between parts, and their share. Random sharding expects 1 - 1/k."""
    at = edges.join(homes.select(F.col("id").alias("src"), F.col("home").alias("hs")), "src").join(homes.select(F.col("id").alias("dst"), F.col("home").alias("hd")), "dst")
    apart = (F.col("hs") != F.col("hd")).cast("long")
    return at.agg(F.coalesce(F.sum(apart), F.lit(0)).alias("cut"), F.avg(apart).alias("rate"))


def proxy_skew(pg: ProxyGraph) -> DataFrame:
    """(role, n, pct): share of each role among the proxies."""
    total = pg.proxies.agg(F.count("*").alias("all"))
    return pg.proxies.groupBy("role").agg(F.count("*").alias("n")).crossJoin(total).select("role", "n", (100 * F.col("n") / F.col("all")).alias("pct"))


def edge_balance(placed: DataFrame) -> DataFrame:
    return placed.groupBy("pid").agg(F.count("*").alias("edges"))


def proxy_bound(pg: ProxyGraph) -> DataFrame:
    """(n): 1 if there are more proxies than twice the mirrors, else 0."""
    m = pg.proxies.agg(F.count("*").alias("p"), F.countDistinct("pid", "id").alias("m"))
    return m.select((F.col("p") > 2 * F.col("m")).cast("long").alias("n"))


def improvement(a: float, b: float) -> float:
    """Relative gain of cut ``a`` over cut ``b``."""
    return 1 - a / b


def ghost_cost(edges: DataFrame, homes: DataFrame) -> DataFrame:
    """(ghosts): distinct (part, remote neighbour) pairs of a shared-state engine over a vertex placement."""
    at = edges.join(homes.select(F.col("id").alias("src"), F.col("home").alias("hs")), "src").join(homes.select(F.col("id").alias("dst"), F.col("home").alias("hd")), "dst").where("hs <> hd")
    ghosts = at.select(F.col("hs").alias("pid"), F.col("dst").alias("id")).unionByName(at.select(F.col("hd").alias("pid"), F.col("src").alias("id")))
    return ghosts.agg(F.countDistinct("pid", "id").alias("ghosts"))


def degree_profile(g: PropertyGraph, buckets: int = 10) -> DataFrame:
    """(bucket, n, edge_share): total degree per decile of vertices, most connected first."""
    ends = g.edges.select(F.col("src").alias("id")).unionByName(g.edges.select(F.col("dst").alias("id")))
    degrees = ends.groupBy("id").agg(F.count("*").alias("d"))
    spread = degrees.groupBy("d").agg(F.count("*").alias("n"))  # one row per distinct degree
    from pyspark.sql import Window

    before = Window.orderBy(F.desc("d")).rowsBetween(Window.unboundedPreceding, -1)
    ranked = spread.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0)))
    totals = spread.agg(F.sum("n").alias("v"), F.sum(F.col("n") * F.col("d")).alias("t"))
    rows = ranked.crossJoin(totals).withColumn("bucket", F.expr(f"(first * {buckets}) div v"))
    return rows.groupBy("bucket").agg(F.sum("n").alias("n"), (F.sum(F.col("n") * F.col("d")) / F.first("t")).alias("edge_share"))


def tail_exponent(g: PropertyGraph) -> DataFrame:
    """(slope): slope of log count against log degree, a rough tail exponent."""
    ends = g.edges.select(F.col("src").alias("id")).unionByName(g.edges.select(F.col("dst").alias("id")))
    spread = ends.groupBy("id").agg(F.count("*").alias("d")).groupBy("d").agg(F.count("*").alias("n"))
    return spread.agg(F.regr_slope(F.ln("n"), F.ln("d")).alias("slope"))
