"""Loaders against plain sets: many parts, several loaders, synchronised rounds."""

import random

import numpy as np
import pytest

from edgefold.partition import greedy


def edges_of(seed, vertices=60, count=500):
    rng = random.Random(seed)
    return sorted({(int(rng.paretovariate(0.7)) % vertices, rng.randrange(vertices)) for _ in range(count)})


@pytest.mark.parametrize("k", [2, 5, 63, 64, 100])
@pytest.mark.parametrize("directed", [True, False])
def test_a_loader_equals_the_rule_over_sets(k, directed):
    edges = edges_of(k)
    random.Random(k).shuffle(edges)
    u, v = (np.array(x) for x in zip(*edges))
    tables = greedy.LoaderTables(k, directed)
    cut = len(edges) // 3
    got = [*tables.place(u[:cut], v[:cut]).tolist(), *tables.place(u[cut:], v[cut:]).tolist()]
    assert got == greedy.brute_place(edges, k, directed)


def brute_rounds(rows, k, directed, sync, delta=greedy.DELTA):
    """(loader, edge_seq) -> part, by sets that all loaders share from the round before."""
    outs, ins, loads, parts = [set() for _ in range(k)], [set() for _ in range(k)], [0] * k, {}
    for r in range(max(s for _, s, *_ in rows) // sync + 1):
        made = []
        for loader in sorted({x[0] for x in rows}):
            own_out, own_in, own = [set(x) for x in outs], [set(x) for x in ins], list(loads)
            for _, s, u, v in sorted(x for x in rows if x[0] == loader and x[1] // sync == r):
                high, low = max(own), min(own)
                f = lambda i: u in own_out[i] if directed else (u in own_out[i] or u in own_in[i])  # noqa: B023, E731
                g = lambda i: v in own_in[i] if directed else (v in own_out[i] or v in own_in[i])  # noqa: B023, E731
                scores = [f(i) + g(i) + (high - own[i]) / (delta + high - low) for i in range(k)]
                i = scores.index(max(scores))
                own_out[i].add(u), own_in[i].add(v)
                own[i] += 1
                made.append((loader, s, u, v, i))
        for loader, s, u, v, i in made:
            parts[loader, s] = i
            outs[i].add(u), ins[i].add(v)
            loads[i] += 1
    return parts


@pytest.mark.parametrize("k,directed", [(4, True), (4, False), (100, True)])
def test_coordinated_loaders_equal_shared_sets(spark, k, directed):
    edges = spark.createDataFrame(edges_of(9, 40, 300), "src long, dst long")
    got = greedy.greedy_place(edges, k, "directed" if directed else "undirected", "coordinated", loaders=2, sync_every=30).collect()
    want = brute_rounds([(r.loader, r.edge_seq, r.src, r.dst) for r in got], k, directed, 30)
    assert len(want) == len(got) and {r.loader for r in got} == {0, 1} and all(r.pid == want[r.loader, r.edge_seq] for r in got)


def test_oblivious_loaders_know_their_own_edges(spark):
    edges = spark.createDataFrame(edges_of(4), "src long, dst long")
    got = greedy.greedy_place(edges, 7, loaders=3).collect()
    for loader in range(3):
        own = sorted((r.edge_seq, r.src, r.dst, r.pid) for r in got if r.loader == loader)
        assert [p for *_, p in own] == greedy.brute_place([(u, v) for _, u, v, _ in own], 7)


def test_rounds_are_bounded_and_empty_lists_placed(spark, monkeypatch):
    monkeypatch.setattr(greedy, "MOST_ROUNDS", 3)
    edges = spark.createDataFrame(edges_of(5, 30, 100), "src long, dst long")
    placed = greedy.greedy_place(edges, 4, ingress="coordinated", loaders=1, sync_every=1)
    assert placed.count() == edges.count()
    none = spark.createDataFrame([], "src long, dst long")
    for ingress in ("serial", "oblivious", "coordinated"):
        assert greedy.greedy_place(none, 4, ingress=ingress).count() == 0
