"""The reference's experiments, re-expressed: each returns rows a plot or table can be made of.

Absolute seconds depend on the machine; what is to be compared is order and trend.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from contextlib import contextmanager
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algorithms import pagerank, traversal
from .baselines import bsp, gas
from .baselines import rounds as comparators
from .graph import build
from .graph.model import PropertyGraph
from .graph.rmat import rmat
from .methods import kept, proxy_graph
from .model.superstep import flat
from .partition import greedy, hashing, measures
from .proxy.exec import mirrored, proxied
from .runtime.metrics import group_share, scaling_slope, speedup
from .runtime.scratch import drop, save
from .runtime.wire import capacity_gigabytes

PLACERS = (("own serial", "directed", "serial"), ("mirror serial", "undirected", "serial"), ("own oblivious", "directed", "oblivious"), ("mirror oblivious", "undirected", "oblivious"))


def _timed(run: Callable[[], object]) -> float:
    began = time.time()
    run()
    return time.time() - began


def rank_engines(spark: SparkSession, g: PropertyGraph, ks: tuple[int, ...] = (2, 4, 8, 16)) -> DataFrame:
    """(engine, k, seconds) of one rank step: the one-sided engine and its comparators, per number of parts."""
    edges = save(pagerank.with_degrees(g), "edges")
    plain = PropertyGraph(g.vertices, edges.select("src", "dst"))
    program = pagerank.rank_program()
    rows = [("flat", 0, _timed(lambda: pagerank.pagerank(plain, 1, arithmetic="scaled"))), ("gas", 0, _timed(lambda: gas.run_gas(edges, g.vertices, program, 1, counted=False))), ("bsp", 0, _timed(lambda: bsp.run_bsp(edges, g.vertices, program, 1))), ("rdd", 0, _timed(lambda: comparators.rdd_pagerank(plain, 1).count()))]
    for k in ks:
        pg = kept(proxy_graph(plain, k))
        for name, strategy in (("proxied", proxied(pg)), ("mirror", mirrored(pg))):
            rows.append((name, k, _timed(lambda s=strategy: pagerank.pagerank(plain, 1, arithmetic="scaled", strategy=s))))
    return spark.createDataFrame(rows, "engine string, k int, seconds double")


def weak_scaling(spark: SparkSession, scales: tuple[int, ...] = (8, 10, 12)) -> DataFrame:
    """(program, size, seconds) of rank steps, distances and components on growing generated graphs."""
    rows = []
    for scale in scales:
        g = rmat(spark, scale)
        size = float((1 << scale) * 16)
        rows.append(("pagerank", size, min(pagerank.pagerank_run(g, 2).timings)))
        rows.append(("sssp", size, sum(traversal.sssp_run(build.with_random_weights(g), 0).timings)))
        rows.append(("components", size, sum(traversal.connected_run(g).timings)))
    return spark.createDataFrame(rows, "program string, size double, seconds double")


def weak_scaling_slopes(spark: SparkSession, scales: tuple[int, ...] = (12, 14, 16)) -> DataFrame:
    """(program, slope): growth of seconds with size, as a power; 1 is in proportion, less is fixed cost being shared."""
    times = save(weak_scaling(spark, scales), "times")
    parts = [scaling_slope(times.where(F.col("program") == p)).select(F.lit(p).alias("program"), "slope") for p in ("pagerank", "sssp", "components")]
    return reduce(DataFrame.unionByName, parts)


@contextmanager
def _at_most(spark: SparkSession, workers: int):
    """Shuffles of ``workers`` partitions meanwhile, so that at most so many tasks of a step run at once."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(workers))
    try:
        yield
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def _saved(g: PropertyGraph) -> PropertyGraph:
    return PropertyGraph(save(g.vertices, "vertices"), save(g.edges, "edges"))


def strong_scaling(spark: SparkSession, scale: int = 14, workers: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """(program, workers, seconds, speedup) of a rank step, distances and components on one graph.

    A session's cores are fixed; what varies is how many tasks a step is dealt to. Loops run once before they are timed.
    """
    g = _saved(rmat(spark, scale))
    weighted = PropertyGraph(g.vertices, build.with_random_weights(g).edges)
    programs = {
        "pagerank": lambda: min(pagerank.pagerank_run(g, 3, write_every=1).timings),
        "sssp": lambda: sum(traversal.sssp_run(weighted, 0).timings),
        "components": lambda: sum(traversal.connected_run(g).timings),
    }
    parts = []
    for name, run in programs.items():
        run()
        rows = []
        for n in workers:
            with _at_most(spark, n):
                rows.append((n, run()))
        parts.append(speedup(spark.createDataFrame(rows, "workers int, seconds double")).select(F.lit(name).alias("program"), "workers", "seconds", "speedup"))
    return reduce(DataFrame.unionByName, parts)


def program_engines(spark: SparkSession, g: PropertyGraph, k: int = 4) -> DataFrame:
    """(program, engine, seconds) of distances and components per engine on one graph; every engine gets saved tables."""
    g = _saved(g)
    weighted, both = PropertyGraph(g.vertices, save(build.with_random_weights(g).edges, "edges")), PropertyGraph(g.vertices, save(g.symmetrize().edges, "edges"))
    source = weighted.edges.agg(F.min("src")).first()[0] or 0
    rows = []
    for name, graph, program, own in (
        ("sssp", weighted, traversal.sssp_program(source), lambda s: traversal.sssp_run(weighted, source, strategy=s)),
        ("components", both, traversal.component_program(), lambda s: traversal.connected_run(both, strategy=s)),
    ):
        pg = kept(proxy_graph(graph, k))
        engines = {
            "flat": lambda: own(flat),
            "proxied": lambda: own(proxied(pg)),
            "mirror": lambda: own(mirrored(pg)),
            "gas": lambda: gas.run_gas(graph.edges, graph.vertices, program, counted=False),
            "bsp": lambda: bsp.run_bsp(graph.edges, graph.vertices, program),
        }
        rows += [(name, engine, _timed(run)) for engine, run in engines.items()]
    return spark.createDataFrame(rows, "program string, engine string, seconds double")


def compute_shares(spark: SparkSession, g: PropertyGraph) -> DataFrame:
    """(program, compute_ms, wait_ms, share): time in tasks that isn't waiting for or writing shuffles."""
    g, rows = _saved(g), []
    weighted = build.with_random_weights(g)
    source = g.edges.agg(F.min("src")).first()[0] or 0
    for name, run in (("pagerank", lambda: pagerank.pagerank_run(g, 5)), ("sssp", lambda: traversal.sssp_run(weighted, source)), ("components", lambda: traversal.connected_run(g))):
        group = f"{name}-{uuid.uuid4().hex}"
        spark.sparkContext.setJobGroup(group, name)
        try:
            run()
        finally:
            spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        compute, wait = group_share(spark, group)
        rows.append((name, compute, wait, compute / max(1.0, compute + wait)))
    return spark.createDataFrame(rows, "program string, compute_ms double, wait_ms double, share double")


def _cuts(spark: SparkSession, graphs: list[PropertyGraph], ks: tuple[int, ...], order: str) -> DataFrame:
    """(graph, placer, k, cut_factor, equivalent_cut, hash_cut, s_pct, c_pct) of each graph's number; all are placed at once."""
    tagged = [g.edges.select(F.lit(i).alias("graph"), "src", "dst") for i, g in enumerate(graphs)]
    edges = save(reduce(DataFrame.unionByName, tagged), "edges")
    ways = [(k, placer, direction, ingress) for k in ks for placer, direction, ingress in PLACERS]
    present = greedy.place_each_way(edges, len(graphs), [(k, direction, ingress) for k, _, direction, ingress in ways], order=order)
    counted = [g.vertices.agg(F.count("*").alias("all")).select(F.lit(i).alias("graph"), "all") for i, g in enumerate(graphs) if g.lone]
    v = reduce(DataFrame.unionByName, counted, spark.createDataFrame([], "graph int, all long"))
    apart = [F.avg(hashing.apart(k).cast("long")).alias(f"h{k}") for k in ks]
    hashed = edges.groupBy("graph").agg(*apart).select("graph", F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"h{k}").alias("hash_cut")) for k in ks))).alias("h")).select("graph", "h.*")
    named = spark.createDataFrame([(i, k, placer, direction == "directed") for i, (k, placer, direction, _) in enumerate(ways)], "way int, k int, placer string, own boolean")
    m = measures.placements(present).join(F.broadcast(named), "way").join(F.broadcast(v), "graph", "left").join(F.broadcast(hashed), ["graph", "k"])
    both = F.col("s") + F.col("c")
    charged = F.when(F.col("own"), both).otherwise(2 * F.col("m"))
    rows = m.select(
        "graph", "placer", "k", (charged / F.coalesce("all", "ends")).alias("cut_factor"), (charged / F.col("e")).alias("equivalent_cut"), "hash_cut",
        (100 * F.col("s") / F.greatest(both, F.lit(1))).alias("s_pct"), (100 * F.col("c") / F.greatest(both, F.lit(1))).alias("c_pct"),
    )
    rows = save(rows, "cuts")
    drop(spark, edges)
    return rows


def cut_factors(spark: SparkSession, g: PropertyGraph, ks: tuple[int, ...] = (2, 4, 8, 16), order: str = "digest") -> DataFrame:
    """(placer, k, cut_factor, equivalent_cut, hash_cut, s_pct, c_pct): four placers, what each is charged, and roles' shares.

    Own placers are charged proxies, mirror placers twice their mirrors.
    """
    return _cuts(spark, [g], ks, order).drop("graph")


def cut_table(spark: SparkSession, sf_dir: str, k: int = 16) -> DataFrame:
    """(graph, placer, ...): :func:`cut_factors` at one k over all graphs."""
    names = list(build.GRAPHS)
    bought = PropertyGraph.from_edges(save(build.purchase(spark, sf_dir).edges, "purchase"))
    made = {"purchase": bought, "purchase_rev": bought.transpose(), "trade": build.trade(spark, sf_dir, bought)}
    rows = _cuts(spark, [made.get(n) or build.GRAPHS[n](spark, sf_dir) for n in names], (k,), "digest")
    drop(spark, bought.edges)
    name = F.element_at(F.array(*map(F.lit, names)), F.col("graph") + 1)
    return rows.select(*(c for c in rows.columns if c != "graph"), name.alias("graph"))


#: Graphs whose memory is modelled.
CAPACITY_GRAPHS = ("handoff", "purchase", "hyperlink", "sharedline", "thread")


def capacity_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(graph, vertices, edges, one_sided_gb, split_gb): modelled memory of runs over the given tables' graphs."""
    rows = []
    for name in CAPACITY_GRAPHS:
        g = build.GRAPHS[name](spark, sf_dir)
        counts = g.vertices.agg(F.count("*").cast("double").alias("vertices")).crossJoin(g.edges.agg(F.count("*").cast("double").alias("edges")))
        v, e = F.col("vertices"), F.col("edges")
        rows.append(counts.select(F.lit(name).alias("graph"), "vertices", "edges", capacity_gigabytes(v, e).alias("one_sided_gb"), capacity_gigabytes(v, e, split_phase=True).alias("split_gb")))
    return reduce(DataFrame.unionByName, rows)
