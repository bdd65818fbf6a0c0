"""Traversals: shortest paths with and without predecessors, levels, components by smallest label."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..model.algebra import MIN, MIN_BY
from ..model.program import VertexProgram
from ..model.superstep import RunResult, Strategy, flat, run
from .contract import contract_components


def sssp_program(source: int | list[int], weight: str = "w", predecessor: bool = False) -> VertexProgram:
    """Label-correcting shortest paths: emit distance + weight, keep the smaller, emit again if it improved."""
    sources = [source] if isinstance(source, int) else source
    at_source = F.col("id").isin(sources)
    if not predecessor:
        return VertexProgram(
            name="sssp",
            result=F.when(at_source, F.lit(0).cast("long")),
            active=at_source,
            outgoing=lambda r: r,
            emit=lambda out, edge: out + edge(weight),
            fold=MIN,
            settle=lambda old, acc: F.least(old, acc),
            rearm=lambda old, new: old.isNull() | (new < old),
            retire=True,
        )
    pair = lambda d, p: F.struct(d.cast("long").alias("dist"), p.cast("long").alias("pred"))
    return VertexProgram(
        name="sssp-pred",
        result=F.when(at_source, pair(F.lit(0), F.lit(None))),
        active=at_source,
        outgoing=lambda r: r["dist"],
        emit=lambda out, edge: pair(out + edge(weight), edge("src")),
        fold=MIN_BY,
        settle=lambda old, acc: F.when(old.isNull() | (acc["dist"] < old["dist"]) | ((acc["dist"] == old["dist"]) & (acc["pred"] < old["pred"])), acc).otherwise(old),
        rearm=lambda old, new: old.isNull() | (new["dist"] < old["dist"]),
        retire=True,
    )


def sssp_run(g: PropertyGraph, source: int | list[int], weight: str = "w", predecessor: bool = False, max_steps: int | None = None, strategy: Strategy = flat, allow_negative: bool = False) -> RunResult:
    """Shortest paths; negative weights need ``allow_negative``, which caps the steps at the vertex count."""
    if allow_negative:
        max_steps = max_steps or g.vertices.count()
    elif g.edges.where(F.col(weight) < 0).limit(1).count():
        raise ValueError("negative weights need allow_negative=True")
    edges = PropertyGraph(g.vertices, g.edges.select("src", "dst", *([weight] if weight not in ("src", "dst") else []))).resident().edges
    try:
        return run(edges, g.vertices, sssp_program(source, weight, predecessor), max_steps, strategy)
    finally:
        edges.unpersist()


def sssp(g: PropertyGraph, source: int | list[int], **options) -> DataFrame:
    """(id, dist) or (id, dist, pred); unreached vertices have nulls."""
    found = sssp_run(g, source, **options).frame
    if options.get("predecessor"):
        return found.select("id", F.col("result.dist").alias("dist"), F.col("result.pred").alias("pred"))
    return found.select("id", F.col("result").alias("dist"))


def bfs(g: PropertyGraph, sources: list[int], strategy: Strategy = flat) -> DataFrame:
    """(id, level) from any of the sources."""
    unit = PropertyGraph(g.vertices, g.edges.select("src", "dst", F.lit(1).cast("long").alias("w")))
    return sssp(unit, sources, strategy=strategy).withColumnRenamed("dist", "level")


def path_to(found: DataFrame, target: int) -> DataFrame:
    """(step, id) from ``target`` back to the source, along predecessors of (id, dist, pred)."""
    found.createOrReplaceTempView("_found_paths")
    walked = f"""
        WITH RECURSIVE walk(step, id, pred) MAX RECURSION LEVEL 100000 AS (
          SELECT 0, id, pred FROM _found_paths WHERE id = {int(target)} AND dist IS NOT NULL
          UNION ALL SELECT w.step + 1, f.id, f.pred FROM walk w JOIN _found_paths f ON f.id = w.pred)
        SELECT cast(step AS bigint) AS step, id FROM walk"""
    return found.sparkSession.sql(walked)


def component_program() -> VertexProgram:
    return VertexProgram(
        name="components",
        result=F.col("id"),
        outgoing=lambda r: r,
        emit=lambda out, edge: out,
        fold=MIN,
        settle=lambda old, acc: F.least(old, acc),
        rearm=lambda old, new: new < old,
        retire=True,
    )


def connected_run(g: PropertyGraph, strategy: Strategy = flat) -> RunResult:
    edges = PropertyGraph(g.vertices, g.symmetrize().edges).resident().edges
    try:
        return run(edges, g.vertices, component_program(), strategy=strategy)
    finally:
        edges.unpersist()


def connected_components(g: PropertyGraph, method: str = "labels", strategy: Strategy = flat) -> DataFrame:
    """(id, label): the smallest id of each vertex's undirected component.

    ``labels`` spreads labels, one step per hop; ``contract`` needs rounds that grow with the logarithm of
    the size and suits long chains.
    """
    if method == "contract":
        hung = contract_components(g.edges)
        return g.vertices.select("id").join(hung, "id", "left").select("id", F.coalesce("label", "id").alias("label"))
    return connected_run(g, strategy).frame.select("id", F.col("result").alias("label"))


def component_summary(labels: DataFrame) -> DataFrame:
    """(label, n): size of every component."""
    return labels.groupBy("label").agg(F.count("*").alias("n"))
