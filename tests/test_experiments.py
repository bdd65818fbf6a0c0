"""Experiments and their measures on small graphs, and the entry without the training-data subpackage."""

import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

from edgefold import registry, workloads
from edgefold.graph import build
from edgefold.graph.rmat import rmat
from edgefold.streaming.graphs import PlacedStream

ROOT = Path(__file__).resolve().parents[1]
TWINS = ["greedy_two_pass_parts", "edgecut_violations", "engine_axes", "approx_neighbours_violations", "stream_greedy_place_serial"]


@pytest.mark.parametrize("name", TWINS)
def test_twins(spark, small, name):
    got = registry.queries()[name](spark, small)
    base = duckdb.connect()
    for path in Path(small).glob("*.parquet"):
        base.execute(f"CREATE VIEW {path.stem} AS SELECT * FROM '{path}'")
    want = base.execute(registry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    rows = [dict(zip(names, r)) for r in want.fetchall()]
    key = lambda r: sorted((k, str(v)) for k, v in r.items())
    assert sorted(names) == sorted(got.columns) and sorted(rows, key=key) == sorted((r.asDict() for r in got.collect()), key=key)


def test_strong_scaling(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    rows = workloads.strong_scaling(spark, 6, (1, 2)).collect()
    assert [(r.program, r.workers) for r in rows] == [(p, w) for p in ("pagerank", "sssp", "components") for w in (1, 2)]
    assert all(r.seconds > 0 and (r.workers > 1 or r.speedup == 1) for r in rows) and spark.conf.get("spark.sql.shuffle.partitions") == before


def test_engines_and_shares(spark, small):
    g = build.handoff(spark, small)
    rows = workloads.program_engines(spark, g, 2).collect()
    assert len(rows) == 10 and all(r.seconds > 0 for r in rows)
    shares = workloads.compute_shares(spark, g).collect()
    assert [r.program for r in shares] == ["pagerank", "sssp", "components"] and all(0 < r.share <= 1 and r.compute_ms > 0 for r in shares)


def test_slopes(spark):
    assert workloads.weak_scaling_slopes(spark, (5, 6)).count() == 3


def test_streamed_placement_takes_every_edge_once(spark, tmp_path):
    edges = rmat(spark, 6).edges.select("src", "dst").distinct()
    edges.repartition(3).write.parquet(str(tmp_path / "edges"))
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "edges"))
    follower = PlacedStream(70, loaders=2)
    placed = follower.follow(stream)
    assert placed.select("src", "dst").exceptAll(edges).count() == 0 and placed.count() == edges.count() == follower.tables.loads.sum()
    assert len(follower.tables.rounds) >= 3 and placed.where("pid < 0 OR pid >= 70").count() == 0


def test_the_entry_works_without_the_subpackage(tmp_path):
    for name in ("edgefold", "__spark_entry__.py"):
        source = ROOT / name
        shutil.copytree(source, tmp_path / name, ignore=shutil.ignore_patterns("llm", "__pycache__")) if source.is_dir() else shutil.copy(source, tmp_path)
    left = tmp_path / "edgefold" / "llm" / "__pycache__"
    left.mkdir(parents=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 150 and not any(n.startswith('op') or n == 'pipeline' for n in q); assert set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
