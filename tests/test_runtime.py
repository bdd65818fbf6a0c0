"""Snapshots, models of cost, scaling measures, growing graphs, entry point."""

import json
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from edgefold.algorithms import pagerank, traversal
from edgefold.graph import build, io
from edgefold.graph.rmat import rmat
from edgefold.model.superstep import run
from edgefold.runtime import metrics, wire
from edgefold.runtime.checkpoint import Checkpointer, checkpoint_stats
from edgefold.runtime.scratch import drop, save
from edgefold.streaming.graphs import GrowingComponents


def test_resume_and_refusal(spark, small, tmp_path):
    g = build.handoff(spark, small)
    edges, program = pagerank.with_degrees(g).persist(), pagerank.rank_program()
    marks = Checkpointer(spark, f"file://{tmp_path}/snap", program.name, every=2)
    whole = {tuple(r) for r in run(edges, g.vertices, program, 5, on_step=marks, fixed=True).frame.collect()}
    step, state = marks.resume()
    assert step == 4
    assert {tuple(r) for r in run(edges, None, program, 1, state=state, fixed=True).frame.collect()} == whole
    assert tuple(checkpoint_stats(marks, 5).first()) == (2, 2 * g.vertices.count(), 1)
    with pytest.raises(ValueError):
        Checkpointer(spark, f"file://{tmp_path}/snap", "another", every=2).resume()
    for part in (Path(tmp_path) / "snap/manifest").glob("part-*"):
        row = json.loads(part.read_text() or "{}")
        part.write_text(json.dumps(row | {"rows": -1}) + "\n")
    for crc in (Path(tmp_path) / "snap/manifest").glob(".*.crc"):
        crc.unlink()
    with pytest.raises(ValueError):
        marks.resume()


def test_scaling_measures(spark):
    times = spark.createDataFrame([(2, 10.0), (4, 5.0), (8, 2.5)], "workers int, seconds double")
    assert [r.speedup for r in metrics.speedup(times).orderBy("workers").collect()] == [1.0, 2.0, 4.0]
    sizes = spark.createDataFrame([(2.0 ** i, 3 * 2.0 ** i) for i in range(5)], "size double, seconds double")
    assert metrics.scaling_slope(sizes).first().slope == pytest.approx(1.0)


def test_capacity_model():
    assert wire.capacity_gigabytes(1e9, 17e9) < 768
    assert wire.capacity_gigabytes(512e6, 8e9, split_phase=True) > 2 * wire.capacity_gigabytes(512e6, 8e9)


def test_compute_share_of_a_log(spark, tmp_path):
    event = {"Event": "SparkListenerTaskEnd", "Task Metrics": {"Executor Run Time": 100, "Shuffle Read Metrics": {"Fetch Wait Time": 20}, "Shuffle Write Metrics": {"Shuffle Write Time": 5_000_000}}}
    (tmp_path / "log").write_text(json.dumps(event) + "\n" + json.dumps({"Event": "Other"}) + "\n")
    assert metrics.compute_share(spark, f"file://{tmp_path}/log").first().share == pytest.approx(0.75)


def test_growing_components_equal_whole(spark, small):
    g = build.sharedline(spark, small)
    grown = GrowingComponents()
    for part in range(3):
        grown.add(g.edges.where(F.col("src") % 3 == part))
    whole = traversal.connected_components(g)
    assert grown.labels.select("id", "label").exceptAll(whole).count() == 0 and grown.labels.count() == whole.count()


def test_rmat_is_skewed_and_repeatable(spark):
    g = rmat(spark, 8)
    assert g.edges.count() == 4096 and g.edges.exceptAll(rmat(spark, 8).edges).count() == 0
    degrees = sorted((r.out_degree for r in g.out_degrees().collect()), reverse=True)
    assert sum(degrees[: len(degrees) // 5]) > 0.5 * 4096
    assert rmat(spark, 6, dedup=True, drop_loops=True, permute=True).edges.where("src = dst").count() == 0


def test_layouts_round_trip(spark, small, tmp_path):
    g = build.trade(spark, small)
    want = sorted(map(tuple, g.edges.select("src", "dst", "w").collect()))
    placed = type(g)(g.vertices, g.edges.withColumn("pid", (F.col("src") % 3).cast("int")))
    io.save_graph(placed, f"file://{tmp_path}/parts", "by_part")
    assert sorted(map(tuple, io.load_graph(spark, f"file://{tmp_path}/parts").edges.select("src", "dst", "w").collect())) == want


def test_bucketed_tables_join_without_exchange(spark, small):
    g = build.trade(spark, small)
    io.save_graph(g, "trade_test", "bucketed", parts=4)
    try:
        again = io.load_graph(spark, "trade_test", "bucketed")
        assert again.edges.count() == g.edges.count() and again.vertices.count() == g.vertices.count()
        joined = again.edges.hint("merge").join(again.vertices.withColumnRenamed("id", "src"), "src")
        assert "hashpartitioning" not in joined._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.sql("DROP TABLE IF EXISTS trade_test_edges")
        spark.sql("DROP TABLE IF EXISTS trade_test_vertices")


def test_scratch_tables_are_dropped(spark):
    kept, gone = save(spark.range(3), "kept"), save(spark.range(3), "gone")
    drop(spark, gone, spark.range(1))
    assert kept.count() == 3
    with pytest.raises(Exception, match="(?i)not exist|FileNotFound|FILE_NOT_EXIST"):
        gone.count()


def test_no_edge_exchange_inside_the_loop(spark, small):
    """Resident edges aren't shuffled again, and messages merge before they are."""
    from edgefold.model.program import seed
    from edgefold.model.superstep import flat

    g = build.handoff(spark, small)
    edges = type(g)(g.vertices, pagerank.with_degrees(g)).resident().edges
    edges.count()
    program = pagerank.rank_program()
    state = seed(g.vertices, program)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = flat(edges, state, program)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "partial_sum" in plan
    head = plan.split("InMemoryTableScan")[0]
    assert head.rstrip().splitlines()[-1].count("Exchange") == 0


def test_entry_gives_rows(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_resident_edges_stay_sorted(spark, small):
    from edgefold.model.program import seed
    from edgefold.model.superstep import messages

    g = build.handoff(spark, small)
    edges = type(g)(g.vertices, pagerank.with_degrees(g)).resident().edges
    edges.count()
    program = pagerank.rank_program()
    joined = messages(edges, seed(g.vertices, program).hint("merge"), program)
    above = joined._jdf.queryExecution().executedPlan().toString().split("InMemoryTableScan")[0]
    assert "SortMergeJoin" in above and "Sort [src" not in above.split("SortMergeJoin")[1]
