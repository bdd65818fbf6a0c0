"""Hand-computed graphs: ranks, distances, labels, proxies and message counts."""

import pytest
from pyspark.sql import functions as F

from edgefold.algorithms import multistage, pagerank, rounds, traversal
from edgefold.baselines import bsp, gas, rounds as comparators
from edgefold.graph.model import PropertyGraph
from edgefold.model.algebra import COLLECT, MIN, SUM, Fold, require_commutative, top_k
from edgefold.model.program import VertexProgram
from edgefold.model.superstep import flat, no_premerge, run, two_level
from edgefold.partition import measures
from edgefold.proxy.exec import message_counts, mirrored, proxied
from edgefold.proxy.graph import ProxyGraph, pick_homes

EDGES = [(0, 1, 4), (0, 2, 1), (2, 1, 2), (1, 3, 5), (2, 3, 8), (3, 4, 3), (5, 0, 1), (6, 7, 1)]
RANK_1 = [1.0, 1.0, 0.575, 1.425, 1.0, 0.15, 0.15, 1.0]
RANK_2 = [0.2775, 0.819375, 0.575, 1.244375, 1.36125, 0.15, 0.15, 0.2775]
DIST = [0, 3, 1, 8, 11, None, None, None]
PRED = [None, 2, 0, 1, 3, None, None, None]
LABEL = [0, 0, 0, 0, 0, 0, 6, 6]


@pytest.fixture(scope="module")
def toy(spark):
    return PropertyGraph(spark.range(8), spark.createDataFrame(EDGES, "src long, dst long, w long"))


def column(df, *names):
    rows = sorted(df.collect(), key=lambda r: r["id"])
    return [r[names[0]] if len(names) == 1 else tuple(r[n] for n in names) for r in rows]


def placed_toy(toy, k=3):
    placed = toy.edges.select("src", "dst", ((F.col("src") + F.col("dst")) % k).cast("int").alias("pid"))
    homes = toy.vertices.select("id", (F.col("id") % k).cast("int").alias("home"))
    return ProxyGraph.from_assignment(placed, homes)


def test_ranks(toy):
    assert column(pagerank.pagerank(toy, 1), "result") == pytest.approx(RANK_1)
    assert column(pagerank.pagerank(toy, 2), "result") == pytest.approx(RANK_2)


def test_every_engine_gives_the_same_ranks(toy):
    pg = placed_toy(toy)
    want = [round(x * 1e9) for x in RANK_2]
    for strategy in (flat, no_premerge, two_level(4), proxied(pg), mirrored(pg)):
        got = column(pagerank.pagerank(toy, 2, arithmetic="scaled", strategy=strategy), "result")
        assert all(abs(a - b) <= 2 for a, b in zip(got, want))
    exact = column(pagerank.pagerank(toy, 3, arithmetic="scaled"), "result")
    edges = pagerank.with_degrees(toy)
    assert column(gas.run_gas(edges, toy.vertices, pagerank.rank_program(), 3).frame, "result") == exact
    for merger in (False, True):
        assert column(bsp.run_bsp(edges, toy.vertices, pagerank.rank_program(), 3, merger)[0], "result") == exact
    assert column(comparators.spmv_pagerank(toy, 3), "result") == exact
    assert column(comparators.mapreduce_pagerank(toy, 3), "result") == exact
    assert column(comparators.rdd_pagerank(toy, 3), "result") == exact


def test_distances_and_predecessors(toy):
    pg = placed_toy(toy)
    for strategy in (flat, no_premerge, proxied(pg), mirrored(pg)):
        assert column(traversal.sssp(toy, 0, strategy=strategy), "dist") == DIST
    assert column(traversal.sssp(toy, 0, predecessor=True), "dist", "pred") == list(zip(DIST, PRED))
    assert column(gas.run_gas(toy.edges, toy.vertices, traversal.sssp_program(0)).frame, "result") == DIST


def test_negative_weights_are_refused_unless_allowed(spark):
    g = PropertyGraph(spark.range(3), spark.createDataFrame([(0, 1, 5), (0, 2, 1), (1, 2, -7)], "src long, dst long, w long"))
    with pytest.raises(ValueError):
        traversal.sssp(g, 0)
    assert column(traversal.sssp(g, 0, allow_negative=True), "dist") == [0, 5, -2]


def test_invariants_are_checked(toy):
    done = run(toy.edges, toy.vertices, traversal.sssp_program(0), debug_invariants=True)
    assert column(done.frame, "result") == DIST and done.frontier == [1, 2, 2, 2, 1]


def test_path_and_levels(toy):
    found = traversal.sssp(toy, 0, predecessor=True)
    assert [r.id for r in traversal.path_to(found, 4).orderBy("step").collect()] == [4, 3, 1, 2, 0]
    assert column(traversal.bfs(toy, [0]), "level") == [0, 1, 1, 2, 3, None, None, None]
    assert column(traversal.bfs(toy, [0, 6]), "level") == [0, 1, 1, 2, 3, None, 0, 1]


def test_components(toy):
    for method in ("labels", "contract"):
        assert column(traversal.connected_components(toy, method), "label") == LABEL


def test_components_of_a_long_chain(spark):
    n = 300
    chain = spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    got = traversal.connected_components(PropertyGraph(spark.range(n), chain), "contract")
    assert got.where("label <> 0").count() == 0 and got.count() == n


def test_strong_components(spark):
    edges = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 3), (4, 5), (6, 6)]
    g = PropertyGraph(spark.range(7), spark.createDataFrame(edges, "src long, dst long"))
    assert column(multistage.strong_components(g), "scc") == [0, 0, 0, 3, 3, 5, 6]


def test_betweenness_of_a_path(spark):
    g = PropertyGraph(spark.range(4), spark.createDataFrame([(0, 1), (1, 2), (2, 3)], "src long, dst long"))
    assert column(multistage.betweenness(g, g.vertices), "score") == [0.0, 2.0, 2.0, 0.0]


def test_forest_and_matching(spark):
    edges = [(0, 1, 1), (1, 2, 2), (0, 2, 3), (3, 4, 7), (2, 0, 9)]
    g = PropertyGraph(spark.range(5), spark.createDataFrame(edges, "src long, dst long, w long"))
    assert sorted(map(tuple, rounds.spanning_forest(g).collect())) == [(0, 1, 1), (1, 2, 2), (3, 4, 7)]
    assert sorted(map(tuple, rounds.weighted_matching(g).collect())) == [(0, 2, 9), (3, 4, 7)]


def test_semi_clusters_of_a_triangle(spark):
    g = PropertyGraph.from_edges(spark.createDataFrame([(0, 1), (1, 2), (0, 2), (2, 3)], "src long, dst long"))
    best = {r.id: (r.cluster, r.score) for r in multistage.semi_clusters(g, max_size=3, top_n=2, boundary=0.2).collect() if len(r.cluster) == 3}
    assert best[0] == ([0, 1, 2], pytest.approx((3 - 0.2) / 3))


def test_degenerate_graphs(spark):
    nobody = spark.createDataFrame([], "src long, dst long, w long")
    g = PropertyGraph(spark.range(2), nobody)
    assert column(pagerank.pagerank(g, 2), "result") == [0.15, 0.15]
    assert column(traversal.sssp(g, 0), "dist") == [0, None]
    assert column(traversal.connected_components(g, "contract"), "label") == [0, 1]
    assert column(multistage.strong_components(g), "scc") == [0, 1]


def proxies_of(spark, edges, homes):
    placed = spark.createDataFrame(edges, "src long, dst long, pid int")
    return ProxyGraph.from_assignment(placed, spark.createDataFrame(homes, "id long, home int"))


def counts(pg, k):
    r = measures.proxy_measures(pg, k).first()
    return r.s, r.c, r.replicas - r.v


def test_fan_in_fan_out_and_third_part(spark):
    homes = [(1, 0), (2, 0), (3, 0), (9, 1)]
    fan_in = proxies_of(spark, [(1, 9, 0), (2, 9, 0), (3, 9, 0)], homes)
    assert counts(fan_in, 2) == (0, 1, 1)
    sent = message_counts(fan_in, fan_in.homes).first()
    assert (sent.emitted, sent.s_msgs, sent.c_msgs) == (3, 0, 1)
    fan_out = proxies_of(spark, [(9, 1, 0), (9, 2, 0), (9, 3, 0)], homes)
    assert counts(fan_out, 2) == (1, 0, 1)
    assert [r.parts for r in fan_out.routing().collect()] == [[0]]
    third = proxies_of(spark, [(1, 9, 2)], homes)
    assert counts(third, 3) == (1, 1, 2) and third.violations().first().n == 0
    assert {(r.id, r.role) for r in third.proxy_edges().collect()} == {(1, "out"), (9, "in")}


def test_half_cost_of_mirrors(spark):
    pg = proxies_of(spark, [(1, 9, 0), (2, 9, 1)], [(1, 0), (2, 1), (9, 2)])
    r = measures.proxy_measures(pg, 3).first()
    assert r.s + r.c == 2 and r.mirror_cut_factor * r.v == 4


def test_local_ids_and_rows_of_a_part(spark):
    pg = proxies_of(spark, [(1, 9, 0), (2, 9, 0), (1, 2, 0)], [(1, 0), (2, 0), (9, 1)])
    local = {(r.pid, r.id): (r.lid, r.role) for r in pg.localize().collect()}
    assert local == {(0, 1): (0, "home"), (0, 2): (1, "home"), (0, 9): (2, "in"), (1, 9): (0, "home")}
    assert [(r.pid, r.lid, r.offset, r.degree, r.targets) for r in pg.to_csr().orderBy("lid").collect()] == [(0, 0, 0, 2, [1, 2]), (0, 1, 2, 1, [2])]


def test_homes_take_most_edges_and_lowest_part(spark):
    placed = spark.createDataFrame([(1, 2, 1), (1, 3, 1), (2, 3, 0)], "src long, dst long, pid int")
    homes = {r.id: r.home for r in pick_homes(placed, spark.range(1, 5), 2).collect()}
    assert homes[1] == 1 and homes[2] == 0 and homes[3] == 0


def test_fold_contracts(toy):
    with pytest.raises(ValueError):
        require_commutative(Fold("last", F.last, lambda xs: xs, commutative=False))
    with pytest.raises(ValueError):
        VertexProgram("x", F.lit(0), lambda r: r, lambda o, e: o, MIN, lambda a, b: b, attributes=("acc",)).validate()
    gathered = VertexProgram("g", F.col("id"), lambda r: F.col("id"), lambda o, e: o, COLLECT, lambda a, b: F.aggregate(b, F.lit(0).cast("long"), lambda x, y: x + y))
    assert column(run(toy.edges, toy.vertices, gathered, 1).frame, "result")[1] == 2
    best = VertexProgram("t", F.array(F.col("id")), lambda r: F.col("id"), lambda o, e: o, top_k(1), lambda a, b: b)
    assert column(run(toy.edges, toy.vertices, best, 1).frame, "result")[3] == [2]


def test_edge_state_subset_and_target_reading(toy):
    counted = VertexProgram("c", F.lit(1).cast("long"), lambda r: r, lambda o, e: o, SUM, lambda a, b: b, emit_where="w > 2", edge_update={"w": lambda o, e: e("w") * 2})
    done = run(toy.edges, toy.vertices, counted, 2)
    assert sorted(r.w for r in done.edges.collect()) == sorted(4 * w for _, _, w in EDGES)
    seen = VertexProgram("n", F.col("id"), lambda r: r, lambda o, e: o, SUM, lambda a, b: b, needs_target=lambda there, payload: there * 100 + payload)
    assert column(run(toy.edges, toy.vertices, seen, 1).frame, "result")[4] == 403


def test_graph_operators(toy):
    assert {(r.src, r.dst) for r in toy.out_edges(toy.vertices.where("id = 0")).collect()} == {(0, 1), (0, 2)}
    assert {(r.src, r.dst) for r in toy.in_edges(toy.vertices.where("id = 3")).collect()} == {(1, 3), (2, 3)}
    assert toy.where_vertices("id < 3").edges.count() == 3 and toy.where_edges("w = 1").edges.count() == 3
    assert toy.transpose().edges.where("src = 1 AND dst = 0").count() == 1
    assert {r.id for r in toy.sources(toy.edges).collect()} == {0, 1, 2, 3, 5, 6} and toy.targets(toy.edges).count() == 6


def test_rank_options(toy, spark):
    ranks, steps = pagerank.pagerank_until(toy, tol=1e-9, dangling="redistribute")
    assert abs(sum(column(ranks, "result")) - 8) < 1e-6 and steps < 100
    only, _ = pagerank.pagerank_until(toy, sources=spark.createDataFrame([(6,)], "id long"))
    assert [x > 0 for x in column(only, "result")] == [False] * 6 + [True, True]
    heavy, _ = pagerank.pagerank_until(toy, weight="w")
    assert column(heavy, "result")[1] > column(heavy, "result")[2]
