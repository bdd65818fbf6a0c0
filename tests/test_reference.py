"""Random graphs: every distributed algorithm against its plain version."""

import pytest

from edgefold.algorithms import multistage, pagerank, rounds, traversal
from edgefold.graph.build import with_random_weights
from edgefold.graph.rmat import rmat
from edgefold.partition import hashing
from edgefold.proxy.exec import mirrored, proxied
from edgefold.proxy.graph import ProxyGraph
from edgefold.reference import exact


@pytest.fixture(scope="module", params=[(5, 2), (6, 4)])
def case(spark, request):
    scale, factor = request.param
    g = with_random_weights(rmat(spark, scale, factor, seed=scale, dedup=True, drop_loops=True))
    g = type(g)(g.vertices, g.edges.persist())
    return g, list(range(1 << scale)), [(r.src, r.dst, r.w) for r in g.edges.collect()]


def as_dict(df, value):
    return {r["id"]: r[value] for r in df.collect()}


def test_ranks(case):
    g, vertices, edges = case
    want = exact.scaled_ranks(vertices, edges, 4)
    assert as_dict(pagerank.pagerank(g, 4, arithmetic="scaled"), "result") == want
    pg = ProxyGraph.from_assignment(hashing.edge_hash_place(g.edges, 3), hashing.hash_homes(g.vertices, 3))
    for strategy in (proxied(pg), mirrored(pg)):
        assert as_dict(pagerank.pagerank(g, 4, arithmetic="scaled", strategy=strategy), "result") == want


def test_paths(case):
    g, vertices, edges = case
    found = {r.id: (r.dist, r.pred) for r in traversal.sssp(g, 0, predecessor=True).collect()}
    assert found == exact.dijkstra(vertices, edges, 0)


def test_components(case):
    g, vertices, edges = case
    want = exact.smallest_labels(vertices, edges)
    for method in ("labels", "contract"):
        assert as_dict(traversal.connected_components(g, method), "label") == want


def test_strong_components(case):
    g, vertices, edges = case
    assert as_dict(multistage.strong_components(g), "scc") == exact.strong_labels(vertices, edges)


def test_betweenness(case):
    g, vertices, edges = case
    want = exact.betweenness(vertices, edges)
    got = as_dict(multistage.betweenness(g, g.vertices), "score")
    assert all(got[v] == pytest.approx(want[v]) for v in vertices)


def test_forest(case):
    g, vertices, edges = case
    tree = rounds.spanning_forest(g).collect()
    labels = exact.smallest_labels(vertices, edges)
    assert len(tree) == len(vertices) - len(set(labels.values())) and sum(r.w for r in tree) == exact.forest_weight(vertices, edges)


def test_matching_is_half_of_the_best_at_least(case):
    g, vertices, edges = case
    taken, greedy = set(), 0
    for w, u, v in sorted(((w, u, v) for u, v, w in edges), reverse=True):
        if not {u, v} & taken:
            taken |= {u, v}
            greedy += w
    matched = rounds.weighted_matching(g).collect()
    assert len({x for r in matched for x in (r.src, r.dst)}) == 2 * len(matched) and sum(r.w for r in matched) == pytest.approx(greedy, rel=0.1)


def test_colours(case):
    g, vertices, edges = case
    colour = as_dict(rounds.colouring(g), "colour")
    assert set(colour) == set(vertices) and all(colour[u] != colour[v] for u, v, _ in edges)
