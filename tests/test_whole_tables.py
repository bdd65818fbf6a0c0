"""Queries over whole tables: nothing beyond a fixed id, source, nation or depth is left out."""

import random
from decimal import Decimal

import numpy as np

from edgefold import registry
from edgefold.graph import build
from edgefold.graph.model import PropertyGraph
from edgefold.reference import exact

LINE = "l_orderkey long, l_partkey long, l_returnflag string, l_linestatus string, l_extendedprice double"


def lines(spark, folder):
    rows = [(o, p, "AR"[o % 2], "OF"[p % 2], 1.25 * p + o) for o in (1, 99, 100, 399, 400, 5000) for p in (o % 7, o % 11 + 3, o % 13 + 20)]
    spark.createDataFrame(rows, LINE).write.parquet(f"{folder}/lineitem.parquet")
    return rows


def test_forest_of_all_orders(spark, tmp_path):
    rows = lines(spark, tmp_path)
    pairs = {(a, b) for o, a, *_ in rows for p, b, *_ in rows if o == p and a < b}
    edges = [(a, b, 1 + (a * 7919 + b * 104729) % 1000003) for a, b in pairs]
    ids = sorted({x for e in edges for x in e[:2]})
    label = {i: i for i in ids}
    for _ in ids:
        for a, b, _w in edges:
            label[a] = label[b] = min(label[a], label[b])
    got = registry.queries()["forest_weight_all"](spark, str(tmp_path)).collect()
    assert [tuple(r) for r in got] == [(len(ids) - len(set(label.values())), exact.forest_weight(ids, edges))]


def test_decimal_sums_of_all_orders(spark, tmp_path):
    rows = lines(spark, tmp_path)
    got = {r.l_returnflag: (r.total, r.closed, r.numeric) for r in registry.queries()["decimal_flow_all"](spark, str(tmp_path)).collect()}
    for flag in "AR":
        own = [r for r in rows if r[2] == flag]
        assert got[flag] == (float(sum(Decimal(str(r[4])) for r in own)), sum(r[3] != "O" for r in own), 0)


def test_betweenness_from_every_source(spark, monkeypatch):
    rows = [(0, 1), (1, 2), (2, 3), (3, 6), (6, 7), (1, 4), (4, 3), (7, 0)]
    monkeypatch.setattr(build, "handoff_strong", lambda spark, sf: PropertyGraph.from_edges(spark.createDataFrame(rows, "src long, dst long")))
    want = exact.betweenness(sorted({x for r in rows for x in r}), [(a, b, 1) for a, b in rows])
    got = {r.id: r.score for r in registry.queries()["betweenness_strong_all"](spark, "").collect()}
    assert got.keys() == want.keys() and all(abs(got[i] - want[i]) < 1e-3 for i in want)


def test_frontiers_of_a_traversal(spark, monkeypatch):
    rows = [(0, 1), (0, 3), (1, 2), (3, 2), (2, 0), (2, 7), (8, 9)]
    monkeypatch.setattr(build, "handoff", lambda spark, sf: PropertyGraph.from_edges(spark.createDataFrame(rows, "src long, dst long")))
    got = sorted(map(tuple, registry.queries()["frontier_edges_traversal"](spark, "").collect()))
    assert got == [(0, 0, 1), (0, 0, 3), (1, 1, 2), (1, 3, 2), (2, 2, 0), (2, 2, 7)]


def test_reachability_beyond_thirty_steps(spark, monkeypatch):
    rows = [(i, i + 1) for i in range(34)] + [(34, 3), (90, 91)]
    monkeypatch.setattr(build, "handoff_strong", lambda spark, sf: PropertyGraph.from_edges(spark.createDataFrame(rows, "src long, dst long").coalesce(1)))
    assert sorted(r.id for r in registry.queries()["sql_reachability"](spark, "").collect()) == list(range(35))


def test_neighbours_chunk_against_chunk(spark, tmp_path):
    rng = random.Random(1)
    rows = [(i, [float(rng.randint(-2, 2)) for _ in range(3)] + [1.0]) for i in range(60)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    unit = {i: np.array(v) / np.linalg.norm(v) for i, v in rows}
    want = {(i, j) for i in unit for j in sorted((j for j in unit if j != i), key=lambda j: (-round(float(unit[i] @ unit[j]), 9), j))[:5]}
    for chunk in (100, 17, 4):
        assert sorted(map(tuple, build.knn(spark, str(tmp_path), 5, chunk=chunk).edges.collect())) == sorted(want)


def test_pivot_has_every_nation(spark, small):
    edges = {(r.src, r.dst): r.w for r in build.trade(spark, small).edges.collect()}
    got = {(r.src, int(c[3:])): r[c] for r in registry.queries()["flow_pivot_all"](spark, small).collect() for c in r.asDict() if c != "src" and r[c]}
    assert got == edges and max(d for _, d in got) > 4
