"""Registered queries of the graph methods, variants, comparators, measures and workloads, with SQL twins."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algorithms import multistage, pagerank, rounds, traversal
from .baselines import bsp, gas
from .baselines import rounds as comparators
from .graph import build
from .graph.model import PropertyGraph
from .graph.rmat import drawn, rmat
from .model.program import ANY_MESSAGE
from .model.superstep import Strategy, flat, no_premerge, two_level
from .oracles import graphs as sql
from .partition import edgecut, greedy, hashing, measures
from .proxy.exec import message_counts, mirrored, proxied
from .proxy.graph import ProxyGraph, pick_homes
from .runtime.checkpoint import Checkpointer
from .runtime.metrics import fold_collisions
from .runtime.scratch import new_path, save
from .runtime.wire import topology_bytes, wire_bytes

K = 8


def _count(df: DataFrame, name: str = "n") -> DataFrame:
    return df.agg(F.count("*").alias(name))


def proxy_graph(g: PropertyGraph, k: int = K, rule: str = "edge") -> ProxyGraph:
    """Proxy graph under arithmetic placement: scrambled homes, and edges by scramble or at an end's home."""
    homes = hashing.hash_homes(g.vertices, k)
    placed = hashing.edge_hash_place(g.edges, k) if rule == "edge" else hashing.place_edges(g.edges, homes, rule)
    return ProxyGraph.from_assignment(placed, homes)


def kept(pg: ProxyGraph) -> ProxyGraph:
    """The same proxy graph with its tables written once, for loops."""
    return ProxyGraph(save(pg.edges, "placed"), save(pg.homes, "homes"), save(pg.proxies, "proxies"))


def _scaled(g: PropertyGraph, steps: int = 10, strategy: Strategy = flat, **options) -> DataFrame:
    return pagerank.pagerank(g, steps, arithmetic="scaled", strategy=strategy, **options).withColumnRenamed("result", "rank_e9")


# ranks


def pagerank_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.handoff(spark, sf))


def pagerank_double_5(spark: SparkSession, sf: str) -> DataFrame:
    return pagerank.pagerank(build.handoff(spark, sf), 5).select("id", F.round("result", 6).alias("rank"))


def pagerank_gas_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    done = gas.run_gas(save(pagerank.with_degrees(g), "edges"), g.vertices, pagerank.rank_program(), 10, counted=False)
    return done.frame.withColumnRenamed("result", "rank_e9")


def _bsp_ranks(merger: bool):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        g = build.handoff(spark, sf)
        frame, _, _ = bsp.run_bsp(save(pagerank.with_degrees(g), "edges"), g.vertices, pagerank.rank_program(), 10, merger)
        return frame.withColumnRenamed("result", "rank_e9")

    return run


def pagerank_mirror_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return _scaled(g, strategy=mirrored(kept(proxy_graph(g))))


def pagerank_proxied_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return _scaled(g, strategy=proxied(kept(proxy_graph(g))))


def pagerank_nopremerge_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.handoff(spark, sf), strategy=no_premerge)


def pagerank_two_level_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.handoff(spark, sf), strategy=two_level())


def pagerank_spmv_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return comparators.spmv_pagerank(build.handoff(spark, sf), 10).withColumnRenamed("result", "rank_e9")


def pagerank_mapreduce_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return comparators.mapreduce_pagerank(build.handoff(spark, sf), 10).withColumnRenamed("result", "rank_e9")


def pagerank_rdd_scaled_10(spark: SparkSession, sf: str) -> DataFrame:
    return comparators.rdd_pagerank(build.handoff(spark, sf), 10).withColumnRenamed("result", "rank_e9")


def pagerank_dangling(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.hyperlink(spark, sf), 5)


def pagerank_fanin(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.purchase(spark, sf), 5)


def pagerank_message_woken(spark: SparkSession, sf: str) -> DataFrame:
    return _scaled(build.hyperlink(spark, sf), 5, wake=ANY_MESSAGE)


def checkpoint_resume_equal(spark: SparkSession, sf: str) -> DataFrame:
    """Ranks after a run that stops at step 6 and goes on from its snapshot of step 5 in a new loop."""
    from .model.superstep import run

    g = build.handoff(spark, sf)
    edges, program = save(pagerank.with_degrees(g), "edges"), pagerank.rank_program()
    marks = Checkpointer(spark, new_path(spark, "snapshots"), program.name, every=5)
    run(edges, g.vertices, program, 6, on_step=marks, fixed=True)
    step, state = marks.resume()
    return run(edges, None, program, 10 - step, state=state, fixed=True).frame.withColumnRenamed("result", "rank_e9")


# traversals


def sssp_dist(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.sssp(build.handoff(spark, sf), 0)


def sssp_weighted_pred(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.sssp(build.with_random_weights(build.handoff(spark, sf)), 0, predecessor=True)


def sssp_unreached(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.sssp(build.thread(spark, sf), 0)


def sssp_proxied(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return traversal.sssp(g, 0, strategy=proxied(kept(proxy_graph(g))))


def sssp_gas(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return gas.run_gas(save(g.edges, "edges"), g.vertices, traversal.sssp_program(0), counted=False).frame.withColumnRenamed("result", "dist")


def sssp_bsp(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return bsp.run_bsp(save(g.edges, "edges"), g.vertices, traversal.sssp_program(0))[0].withColumnRenamed("result", "dist")


def sssp_triangle_violations(spark: SparkSession, sf: str) -> DataFrame:
    g = build.with_random_weights(build.handoff(spark, sf))
    d = save(traversal.sssp(g, 0), "dist")
    at = g.edges.join(d.select(F.col("id").alias("src"), F.col("dist").alias("a")), "src").join(d.select(F.col("id").alias("dst"), F.col("dist").alias("b")), "dst")
    return _count(at.where("a IS NOT NULL AND (b IS NULL OR b > a + w)"))


def bfs_levels(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.bfs(build.handoff_strong(spark, sf), [0])


def path_to_vertex(spark: SparkSession, sf: str) -> DataFrame:
    found = save(traversal.sssp(build.with_random_weights(build.handoff(spark, sf)), 0, predecessor=True), "paths")
    return traversal.path_to(found, 7)


def _components(graph: str, method: str = "labels"):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return traversal.connected_components(build.GRAPHS[graph](spark, sf), method)

    return run


def cc_sizes(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.component_summary(traversal.connected_components(build.sharedline(spark, sf)))


def cc_proxied(spark: SparkSession, sf: str) -> DataFrame:
    g = build.sharedline(spark, sf)
    both = g.symmetrize()
    return traversal.connected_components(g, strategy=proxied(kept(proxy_graph(both))))


def cc_gas(spark: SparkSession, sf: str) -> DataFrame:
    g = build.sharedline(spark, sf).symmetrize()
    return gas.run_gas(save(g.edges, "edges"), g.vertices, traversal.component_program(), counted=False).frame.withColumnRenamed("result", "label")


def cc_rmat8(spark: SparkSession, sf: str) -> DataFrame:
    return traversal.connected_components(rmat(spark, 8))


def rmat_scale8_degrees(spark: SparkSession, sf: str) -> DataFrame:
    """(id, out_degree) of the recursive-matrix graph with one edge drawn by each event's number."""
    numbers = build.table(spark, sf, "events").select(F.col("event_id").alias("edge_seq"))
    return PropertyGraph.from_edges(drawn(numbers, 8)).out_degrees()


def convergence_trace(spark: SparkSession, sf: str) -> DataFrame:
    """(step, frontier): emitting vertices per step of components on chains."""
    done = traversal.connected_run(build.thread(spark, sf))
    return spark.createDataFrame(list(enumerate(done.frontier)), "step long, frontier long")


# multi-stage algorithms


def scc_strong(spark: SparkSession, sf: str) -> DataFrame:
    return multistage.strong_components(build.handoff_strong(spark, sf))


def betweenness_strong_all(spark: SparkSession, sf: str) -> DataFrame:
    """(id, score) over the shortest paths from every vertex."""
    g = build.handoff_strong(spark, sf)
    g = PropertyGraph(save(g.vertices, "vertices"), save(g.edges, "edges"))
    return multistage.betweenness(g, g.vertices).select("id", F.round("score", 4).alias("score"))


def _matching(spark: SparkSession, sf: str) -> tuple[PropertyGraph, DataFrame]:
    g = build.part_supplier(spark, sf)
    return g, save(multistage.bipartite_matching(g), "matching")


def bipartite_matching_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): ends matched twice and matched pairs that are no edges."""
    g, m = _matching(spark, sf)
    twice = m.groupBy("src").count().where("count > 1").select("count").unionByName(m.groupBy("dst").count().where("count > 1").select("count"))
    return _count(twice.unionByName(m.join(g.edges, ["src", "dst"], "left_anti").select(F.lit(1).cast("long").alias("count"))))


def matching_maximal_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): edges with both ends free."""
    g, m = _matching(spark, sf)
    return _count(g.edges.join(m.select("src"), "src", "left_anti").join(m.select("dst"), "dst", "left_anti"))


def semi_clusters_thread(spark: SparkSession, sf: str) -> DataFrame:
    return multistage.semi_clusters(build.thread(spark, sf))


def forest_weight_all(spark: SparkSession, sf: str) -> DataFrame:
    """(edges, weight): size and weight of a minimum spanning forest of parts bought together in any order."""
    return rounds.spanning_forest(build.copurchase(spark, sf)).agg(F.count("*").alias("edges"), F.coalesce(F.sum("w"), F.lit(0)).alias("weight"))


def colouring_violations(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff_strong(spark, sf)
    c = save(rounds.colouring(g), "colours")
    clash = g.edges.where("src <> dst").join(c.select(F.col("id").alias("src"), F.col("colour").alias("a")), "src").join(c.select(F.col("id").alias("dst"), F.col("colour").alias("b")), "dst").where("a = b")
    missing = g.vertices.join(c, "id", "left_anti")
    return _count(clash.select("src").unionByName(missing.select(F.col("id").alias("src"))))


def weighted_matching_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): vertices matched twice, and edges heavier than every matched edge at their ends."""
    g = build.handoff_strong(spark, sf)
    m = save(rounds.weighted_matching(g), "matching")
    ends = m.select(F.col("src").alias("v"), "w").unionByName(m.select(F.col("dst").alias("v"), "w"))
    twice = ends.groupBy("v").count().where("count > 1").select("v")
    held = ends.groupBy("v").agg(F.max("w").alias("h"))
    at = g.edges.join(held.select(F.col("v").alias("src"), F.col("h").alias("hs")), "src", "left").join(held.select(F.col("v").alias("dst"), F.col("h").alias("hd")), "dst", "left")
    better = at.where("src <> dst AND w > greatest(coalesce(hs, -1), coalesce(hd, -1))")
    return _count(twice.unionByName(better.select(F.col("src").alias("v"))))


# placement


def place_hash_edge_cut(spark: SparkSession, sf: str) -> DataFrame:
    g = build.purchase(spark, sf)
    rows = [measures.edge_cut(g.edges, hashing.hash_homes(g.vertices, k)).select(F.lit(k).alias("k"), "cut", F.round("rate", 6).alias("rate")) for k in (4, 8, 16)]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def _measures(k: int):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = []
        for name in ("handoff", "purchase"):
            g = build.GRAPHS[name](spark, sf)
            pg = proxy_graph(g, k)
            cut = measures.edge_cut(g.edges, pg.homes).select("cut")
            rows.append(measures.proxy_measures(pg, k).crossJoin(cut).select(F.lit(name).alias("graph"), "k", "v", "e", "s", "c", "replicas", "max_load", "cut"))
        return rows[0].unionByName(rows[1])

    return run


def _placed(rule: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = []
        for name in ("purchase", "purchase_rev"):
            g = build.GRAPHS[name](spark, sf)
            pg = proxy_graph(g, K, rule)
            counts = pg.proxies.agg(F.count("*").alias("proxies")).crossJoin(measures.edge_cut(g.edges, pg.homes).select("cut"))
            rows.append(counts.select(F.lit(name).alias("graph"), F.lit(K).alias("k"), "proxies", "cut"))
        return rows[0].unionByName(rows[1])

    return run


def proxy_gain(spark: SparkSession, sf: str) -> DataFrame:
    """(graph, rule, gain): cut edges per proxy that replaces them."""
    rows = []
    for name in ("purchase", "purchase_rev"):
        g = build.GRAPHS[name](spark, sf)
        for rule in ("at_source", "at_target"):
            pg = proxy_graph(g, K, rule)
            both = pg.proxies.agg(F.count("*").alias("p")).crossJoin(measures.edge_cut(g.edges, pg.homes).select("cut"))
            rows.append(both.select(F.lit(name).alias("graph"), F.lit(rule).alias("rule"), F.round(F.col("cut") / F.col("p"), 6).alias("gain")))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def min_proxy_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): 1 for each graph on which the cheaper-side rule needs more proxies than the better plain rule."""
    worse = 0
    for name in ("purchase", "purchase_rev", "hyperlink"):
        g = build.GRAPHS[name](spark, sf)
        n = {r: proxy_graph(g, K, r).proxies.count() for r in ("at_source", "at_target", "min_proxy")}
        worse += n["min_proxy"] > min(n["at_source"], n["at_target"])
    return spark.range(1).select(F.lit(worse).cast("long").alias("n"))


def proxy_skew(spark: SparkSession, sf: str) -> DataFrame:
    rows = []
    for name in ("purchase", "purchase_rev", "hyperlink"):
        skew = measures.proxy_skew(proxy_graph(build.GRAPHS[name](spark, sf)))
        rows.append(skew.select(F.lit(name).alias("graph"), "role", "n", F.round("pct", 4).alias("pct")))
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def edge_balance(spark: SparkSession, sf: str) -> DataFrame:
    return measures.edge_balance(hashing.edge_hash_place(build.handoff(spark, sf).edges, K))


def proxy_bound_violations(spark: SparkSession, sf: str) -> DataFrame:
    rows = [measures.proxy_bound(proxy_graph(build.GRAPHS[n](spark, sf))) for n in ("handoff", "purchase", "hyperlink", "sharedline", "thread")]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out.agg(F.sum("n").alias("n"))


def proxy_rows(spark: SparkSession, sf: str) -> DataFrame:
    return proxy_graph(build.trade(spark, sf), 4).rows()


def proxy_direction_violations(spark: SparkSession, sf: str) -> DataFrame:
    return proxy_graph(build.handoff(spark, sf)).violations()


def routing_lists(spark: SparkSession, sf: str) -> DataFrame:
    lists = proxy_graph(build.trade(spark, sf), 4).routing()
    return lists.select("id", F.array_join(F.transform("parts", lambda x: x.cast("string")), ",").alias("parts"))


def local_ids(spark: SparkSession, sf: str) -> DataFrame:
    return proxy_graph(build.trade(spark, sf), 4).localize()


def csr_rows(spark: SparkSession, sf: str) -> DataFrame:
    rows = proxy_graph(build.trade(spark, sf), 4).to_csr()
    return rows.select("pid", "lid", "offset", F.col("degree").cast("long").alias("degree"), F.array_join(F.transform("targets", lambda x: x.cast("string")), ",").alias("targets"))


def objective_rows(spark: SparkSession, sf: str) -> DataFrame:
    pg = proxy_graph(build.purchase(spark, sf))
    return measures.objective(pg, K).select(F.round("avg_proxies", 4).alias("avg_proxies"), "max_load", "feasible")


def ghost_counts(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    return measures.ghost_cost(g.edges, hashing.hash_homes(g.vertices, K))


def _greedy(order: str, direction: str = "directed"):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        g = build.trade(spark, sf)
        return greedy.greedy_place(g.edges, 4, direction, "serial", order=order).select("edge_seq", "src", "dst", "pid")

    return run


def greedy_oblivious_trade(spark: SparkSession, sf: str) -> DataFrame:
    g = build.trade(spark, sf)
    return greedy.greedy_place(g.edges, 4, ingress="oblivious", loaders=2, order="mixed").select("edge_seq", "src", "dst", "loader", "pid")


def greedy_coordinated_trade(spark: SparkSession, sf: str) -> DataFrame:
    """One loader that merges its tables every 100 edges places as the serial loader does."""
    g = build.trade(spark, sf)
    return greedy.greedy_place(g.edges, 4, ingress="coordinated", loaders=1, order="mixed", sync_every=100).select("edge_seq", "src", "dst", "pid")


def greedy_two_pass_loads(spark: SparkSession, sf: str) -> DataFrame:
    g = build.trade(spark, sf)
    return _count(greedy.greedy_place(g.edges, 4, ingress="serial", two_pass=True), "edges")


def greedy_two_pass_parts(spark: SparkSession, sf: str) -> DataFrame:
    """Every edge's part when a first pass counts degrees and the second streams edges of high-degree vertices first."""
    g = build.trade(spark, sf)
    return greedy.greedy_place(g.edges, 4, ingress="serial", two_pass=True).select("edge_seq", "src", "dst", "pid")


def edgecut_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): vertices that some edge-cut method places never, twice, or in no part, over all methods."""
    g = build.sharedline(spark, sf)
    bad = []
    for m in ("hash", "range", "chunk", "balanced", "ldg", "fennel"):
        homes = edgecut.vertex_partition(g, K, m).groupBy("id").agg(F.count("*").alias("times"), F.min("home").alias("lo"), F.max("home").alias("hi"))
        bad.append(g.vertices.select("id").join(homes, "id", "full").where(f"times IS NULL OR times <> 1 OR lo < 0 OR hi >= {K}").agg(F.count("*").alias("n")))
    return reduce(DataFrame.unionByName, bad).agg(F.sum("n").alias("n"))


def greedy_guarded_balance_violations(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    placed = greedy.greedy_place(g.edges, 4, ingress="serial", order="source", capacity_guard=0.1)
    top = placed.groupBy("pid").agg(F.count("*").alias("n")).agg(F.max("n").alias("top"), F.sum("n").alias("e"))
    return top.select((F.col("top") > 1.1 * F.col("e") / 4 + 1).cast("long").alias("n"))


def greedy_measures_hyperlink(spark: SparkSession, sf: str) -> DataFrame:
    """(placer, k, s, c, mirrors, cut_factor, mirror_cut_factor): four placers, k = 4 and 16."""
    g = build.hyperlink(spark, sf)
    rows = []
    for k in (4, 16):
        for placer, direction, ingress in (("own serial", "directed", "serial"), ("mirror serial", "undirected", "serial"), ("own oblivious", "directed", "oblivious"), ("mirror oblivious", "undirected", "oblivious")):
            placed = save(greedy.greedy_place(g.edges, k, direction, ingress, order="digest"), "placed")
            pg = ProxyGraph.from_assignment(placed, pick_homes(placed, g.vertices, k))
            m = measures.proxy_measures(pg, k)
            rows.append(m.select(F.lit(placer).alias("placer"), "k", "s", "c", (F.col("replicas") - F.col("v")).alias("mirrors"), F.round("cut_factor", 4).alias("cut_factor"), F.round("mirror_cut_factor", 4).alias("mirror_cut_factor")))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def edgecut_methods(spark: SparkSession, sf: str) -> DataFrame:
    """(method, cut, rate) of the streaming edge-cut heuristics on shared lines."""
    g = build.sharedline(spark, sf)
    rows = [measures.edge_cut(g.edges, edgecut.vertex_partition(g, K, m)).select(F.lit(m).alias("method"), "cut", F.round("rate", 6).alias("rate")) for m in ("hash", "range", "chunk", "balanced", "ldg", "fennel")]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


# costs


def step_message_counts(spark: SparkSession, sf: str) -> DataFrame:
    g = build.purchase(spark, sf)
    return message_counts(proxy_graph(g, 4), g.vertices)


def gas_touch_counts(spark: SparkSession, sf: str) -> DataFrame:
    """(touches, stored_rows) of three rank steps with split phases; the one-sided engine touches each edge once."""
    g = build.handoff(spark, sf)
    done = gas.run_gas(save(pagerank.with_degrees(g), "edges"), g.vertices, pagerank.rank_program(), 3)
    return spark.createDataFrame([(done.touches, sum(done.stored))], "touches long, stored_rows long")


def wire_bytes_purchase(spark: SparkSession, sf: str) -> DataFrame:
    return wire_bytes(proxy_graph(build.purchase(spark, sf), 4), capacity=1024)


def topology_bytes_purchase(spark: SparkSession, sf: str) -> DataFrame:
    return topology_bytes(proxy_graph(build.purchase(spark, sf), 4))


def fold_collision_counts(spark: SparkSession, sf: str) -> DataFrame:
    return fold_collisions(build.handoff(spark, sf).edges)


def degree_profiles(spark: SparkSession, sf: str) -> DataFrame:
    rows = [measures.degree_profile(build.GRAPHS[n](spark, sf)).select(F.lit(n).alias("graph"), "bucket", "n", F.round("edge_share", 4).alias("edge_share")) for n in ("sharedline", "purchase")]
    return rows[0].unionByName(rows[1])


def engine_axes(spark: SparkSession, sf: str) -> DataFrame:
    return comparators.engine_axes(proxy_graph(build.handoff(spark, sf)))


def sql_reachability(spark: SparkSession, sf: str) -> DataFrame:
    """Ids reachable from 0, by SQL over the registered views, one query a level until none is new; none if 0 is no vertex."""
    g = build.handoff_strong(spark, sf)
    PropertyGraph(g.vertices, save(g.edges.select("src", "dst"), "strong")).register("strong")
    fresh = reached = save(spark.sql("SELECT DISTINCT 0L AS id FROM strong_edges WHERE src = 0 OR dst = 0"), "walk")
    while fresh.limit(1).count():
        step = spark.sql("SELECT DISTINCT e.dst AS id FROM {fresh} w JOIN strong_edges e ON e.src = w.id LEFT ANTI JOIN {reached} r ON r.id = e.dst", fresh=fresh, reached=reached)
        fresh = save(step, "walk")
        reached = reached.unionByName(fresh)
    return reached


def cosine_knn16(spark: SparkSession, sf: str) -> DataFrame:
    return build.knn(spark, sf).edges


def knn_degrees(spark: SparkSession, sf: str) -> DataFrame:
    """(out_degree, n): every vector has 16 neighbours."""
    return build.knn(spark, sf).out_degrees().groupBy("out_degree").agg(F.count("*").alias("n"))


QUERIES = {
    "pagerank_scaled_10": pagerank_scaled_10,
    "pagerank_double_5": pagerank_double_5,
    "pagerank_gas_scaled_10": pagerank_gas_scaled_10,
    "pagerank_bsp_scaled_10": _bsp_ranks(False),
    "pagerank_bsp_merged_scaled_10": _bsp_ranks(True),
    "pagerank_mirror_scaled_10": pagerank_mirror_scaled_10,
    "pagerank_proxied_scaled_10": pagerank_proxied_scaled_10,
    "pagerank_nopremerge_scaled_10": pagerank_nopremerge_scaled_10,
    "pagerank_two_level_scaled_10": pagerank_two_level_scaled_10,
    "pagerank_spmv_scaled_10": pagerank_spmv_scaled_10,
    "pagerank_mapreduce_scaled_10": pagerank_mapreduce_scaled_10,
    "pagerank_rdd_scaled_10": pagerank_rdd_scaled_10,
    "pagerank_dangling": pagerank_dangling,
    "pagerank_fanin": pagerank_fanin,
    "pagerank_message_woken": pagerank_message_woken,
    "checkpoint_resume_equal": checkpoint_resume_equal,
    "sssp_dist": sssp_dist,
    "sssp_weighted_pred": sssp_weighted_pred,
    "sssp_unreached": sssp_unreached,
    "sssp_proxied": sssp_proxied,
    "sssp_gas": sssp_gas,
    "sssp_bsp": sssp_bsp,
    "sssp_triangle_violations": sssp_triangle_violations,
    "bfs_levels": bfs_levels,
    "path_to_vertex": path_to_vertex,
    "cc_sharedline": _components("sharedline"),
    "cc_thread": _components("thread"),
    "cc_hyperlink": _components("hyperlink"),
    "cc_purchase": _components("purchase"),
    "cc_sizes": cc_sizes,
    "cc_contract": _components("thread", "contract"),
    "cc_proxied": cc_proxied,
    "cc_gas": cc_gas,
    "cc_rmat8": cc_rmat8,
    "rmat_scale8_degrees": rmat_scale8_degrees,
    "convergence_trace": convergence_trace,
    "scc_strong": scc_strong,
    "betweenness_strong_all": betweenness_strong_all,
    "bipartite_matching_violations": bipartite_matching_violations,
    "matching_maximal_violations": matching_maximal_violations,
    "semi_clusters_thread": semi_clusters_thread,
    "forest_weight_all": forest_weight_all,
    "colouring_violations": colouring_violations,
    "weighted_matching_violations": weighted_matching_violations,
    "place_hash_edge_cut": place_hash_edge_cut,
    "proxy_measures_k4": _measures(4),
    "proxy_measures_k8": _measures(8),
    "proxy_measures_k16": _measures(16),
    "place_at_source": _placed("at_source"),
    "place_at_target": _placed("at_target"),
    "proxy_gain": proxy_gain,
    "min_proxy_violations": min_proxy_violations,
    "proxy_skew": proxy_skew,
    "edge_balance": edge_balance,
    "proxy_bound_violations": proxy_bound_violations,
    "proxy_direction_violations": proxy_direction_violations,
    "proxy_rows": proxy_rows,
    "routing_lists": routing_lists,
    "local_ids": local_ids,
    "csr_rows": csr_rows,
    "objective_rows": objective_rows,
    "ghost_counts": ghost_counts,
    "greedy_assign_trade": _greedy("source"),
    "greedy_assign_trade_mixed": _greedy("mixed"),
    "greedy_mirror_assign_trade": _greedy("mixed", "undirected"),
    "greedy_oblivious_trade": greedy_oblivious_trade,
    "greedy_coordinated_trade": greedy_coordinated_trade,
    "greedy_two_pass_parts": greedy_two_pass_parts,
    "edgecut_violations": edgecut_violations,
    "greedy_two_pass_loads": greedy_two_pass_loads,
    "greedy_guarded_balance_violations": greedy_guarded_balance_violations,
    "greedy_measures_hyperlink": greedy_measures_hyperlink,
    "edgecut_methods": edgecut_methods,
    "message_counts": step_message_counts,
    "gas_touch_counts": gas_touch_counts,
    "wire_bytes": wire_bytes_purchase,
    "topology_bytes": topology_bytes_purchase,
    "fold_collisions": fold_collision_counts,
    "degree_profile": degree_profiles,
    "engine_axes": engine_axes,
    "sql_reachability": sql_reachability,
    "cosine_knn16": cosine_knn16,
    "knn_degrees": knn_degrees,
}
