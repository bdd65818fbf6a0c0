"""Placement: the loader against the rule over plain sets, orders, guards, trends, proxy properties."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgefold.graph import build
from edgefold.graph.rmat import rmat
from edgefold.partition import edgecut, greedy, hashing, measures
from edgefold.partition.greedy import LoaderTables, brute_place
from edgefold.proxy.graph import ProxyGraph, pick_homes


@pytest.mark.parametrize("directed", [True, False])
@pytest.mark.parametrize("k", [1, 2, 4, 7])
def test_loader_equals_the_rule(directed, k):
    rng = random.Random(k)
    edges = [(rng.randrange(30), rng.randrange(30)) for _ in range(400)]
    u, v = np.array(edges).T
    assert LoaderTables(k, directed).place(u, v).tolist() == brute_place(edges, k, directed)


def test_loads_of_the_fixture(spark, middle):
    g = build.trade(spark, middle)
    loads = lambda **o: sorted(r["count"] for r in greedy.greedy_place(g.edges, 4, ingress="serial", **o).groupBy("pid").count().collect())
    assert loads(order="source") == [300, 300] and loads(order="mixed") == [79, 80, 108, 333]
    assert loads(order="mixed", direction="undirected") == [194, 203, 203] and loads(order="source", direction="undirected") == [600]


def test_guard_bounds_loads(spark, middle):
    g = build.handoff(spark, middle)
    for ingress in ("serial", "oblivious"):
        placed = greedy.greedy_place(g.edges, 4, ingress=ingress, loaders=3, order="source", capacity_guard=0.1)
        assert max(r["count"] for r in placed.groupBy("pid").count().collect()) <= 1.1 * g.edges.count() / 4 + 3


def measured(g, k, **options):
    placed = greedy.greedy_place(g.edges, k, **options).persist()
    assert placed.count() == g.edges.count()
    pg = ProxyGraph.from_assignment(placed, pick_homes(placed, g.vertices, k))
    return measures.proxy_measures(pg, k).first()


def test_published_order_of_placers(spark):
    """Own serial < mirror serial < own oblivious < mirror oblivious in cut-factor, and all gain on hashing."""
    g = rmat(spark, 10, seed=3)
    for k in (4, 16):
        own = measured(g, k, ingress="serial", order="digest").cut_factor
        mirror = measured(g, k, direction="undirected", ingress="serial", order="digest").mirror_cut_factor
        own_apart = measured(g, k, ingress="oblivious", order="digest", loaders=k).cut_factor
        mirror_apart = measured(g, k, direction="undirected", ingress="oblivious", order="digest", loaders=k).mirror_cut_factor
        hashed = measures.edge_cut(g.edges, hashing.hash_homes(g.vertices, k)).first().cut / g.vertices.count()
        assert own < mirror < own_apart < mirror_apart and own < hashed


def test_coordinated_lies_between(spark):
    g = rmat(spark, 8, seed=3)
    serial, between, apart = (measured(g, 8, ingress=i, order="digest", loaders=4, **o).cut_factor for i, o in (("serial", {}), ("coordinated", {"sync_every": 128}), ("oblivious", {})))
    assert serial <= between <= apart


def test_proxy_properties(spark, middle):
    g = build.purchase(spark, middle)
    for k in (1, 4):
        for rule in ("at_source", "at_target", "min_proxy"):
            homes = hashing.hash_homes(g.vertices, k)
            pg = ProxyGraph.from_assignment(hashing.place_edges(g.edges, homes, rule), homes)
            m = measures.proxy_measures(pg, k).first()
            assert m.e == g.edges.count() and m.s + m.c <= 2 * (m.replicas - m.v) and pg.violations().first().n == 0
            assert (k > 1) == (m.s + m.c > 0)
            assert m.equivalent_cut == pytest.approx(m.proxy_rate / (m.e / m.v))


def test_one_way_bipartite_mirrors_cost_exactly_twice(spark, middle):
    g = build.hyperlink(spark, middle)
    m = measured(g, 4, ingress="serial", order="digest")
    assert (m.s, m.c) == (162, 137) and m.mirror_cut_factor == pytest.approx(2 * m.cut_factor)


def test_edge_cut_methods_place_every_vertex(spark, middle):
    g = build.sharedline(spark, middle)
    cuts = {}
    for method in ("hash", "range", "chunk", "balanced", "ldg", "fennel"):
        homes = edgecut.vertex_partition(g, 4, method)
        assert homes.count() == g.vertices.count() and homes.select("id").distinct().count() == g.vertices.count()
        assert homes.where((F.col("home") < 0) | (F.col("home") > 3)).count() == 0
        cuts[method] = measures.edge_cut(g.edges, homes).first().rate
    assert cuts["ldg"] < cuts["hash"] and abs(cuts["hash"] - 0.75) < 0.05


def test_split_of_mirrors(spark, middle):
    g = build.handoff(spark, middle)
    homes = hashing.hash_homes(g.vertices, 4)
    pg = ProxyGraph.from_assignment(hashing.edge_hash_place(g.edges, 4), homes)
    again = ProxyGraph.from_mirrors(pg.edges, homes, pg.mirrors())
    assert again.proxies.exceptAll(pg.proxies).count() == 0 and again.proxies.count() == pg.proxies.count()
