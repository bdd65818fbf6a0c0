"""Edges of the proxied and mirrored engines stay where they are laid out, and figures come with the write."""

import pytest
from pyspark.sql import Observation
from pyspark.sql import functions as F

from edgefold.algorithms import pagerank, traversal
from edgefold.graph import build
from edgefold.methods import kept, proxy_graph
from edgefold.model.program import seed
from edgefold.proxy.exec import mirrored, proxied
from edgefold.runtime.scratch import save


@pytest.mark.parametrize("make", [proxied, mirrored])
def test_no_edge_exchange_inside_a_step(spark, small, make):
    g = build.handoff(spark, small)
    strategy = make(kept(proxy_graph(g)))
    strategy.begin(save(pagerank.with_degrees(g), "edges"))
    strategy.edges.count(), strategy.routes.count()
    state = save(seed(g.vertices, pagerank.rank_program()), "state")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        plan = strategy(strategy.edges, state, pagerank.rank_program())._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.unset("spark.sql.adaptive.enabled")
        strategy.end()
    shown = plan.splitlines()
    at = next(i for i, line in enumerate(shown) if "InMemoryTableScan" in line and "dst" in line)
    depth = lambda line: len(line) - len(line.lstrip(" :+-*|0123456789()"))
    above, level = [], depth(shown[at])
    for line in reversed(shown[:at]):  # the operators between the edges and their join
        if depth(line) < level:
            level = depth(line)
            above.append(line)
            if "Join" in line:
                break
    assert above and "Join" in above[-1] and not any("Exchange" in x or "Sort " in x for x in above)


def test_all_engines_agree(spark, small):
    g = build.handoff(spark, small)
    want = {tuple(r) for r in pagerank.pagerank(g, 7, arithmetic="scaled").collect()}
    pg = kept(proxy_graph(g))
    for strategy in (proxied(pg), mirrored(pg)):
        for _ in range(2):  # a strategy can run again
            assert {tuple(r) for r in pagerank.pagerank(g, 7, arithmetic="scaled", strategy=strategy).collect()} == want
    far = {tuple(r) for r in traversal.sssp(g, 0).collect()}
    assert {tuple(r) for r in traversal.sssp(g, 0, strategy=mirrored(pg)).collect()} == far


def test_figures_come_with_the_write(spark):
    seen = Observation()
    frame = save(spark.range(100).repartition(7), "figures", seen, F.count_if(F.col("id") < 30).alias("few"))
    assert seen.get["few"] == 30 and frame.count() == 100
