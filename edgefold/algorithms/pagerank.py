"""PageRank: rank = 0.15 + 0.85 * sum(rank / out-degree) over in-neighbours, in doubles or exact units."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..model.algebra import SUM
from ..model.program import ALL, ANY_MESSAGE, VertexProgram
from ..model.superstep import RunResult, Strategy, flat, no_premerge, run

UNIT = 1_000_000_000


def rank_program(arithmetic: str = "scaled", damping: int = 85, wake: str = ALL, init: float = 1.0) -> VertexProgram:
    """The program; ``scaled`` counts in billionths with whole division, so any order gives the same sum."""
    scaled = arithmetic == "scaled"
    if scaled:
        emit = lambda out, edge: F.expr("_out div _degree")
        settle = lambda old, acc: F.expr(f"{(100 - damping) * UNIT // 100}L + ({damping} * coalesce(acc, 0L)) div 100")
        first = F.lit(int(init * UNIT)).cast("long")
    else:
        emit = lambda out, edge: out / edge("_degree")
        settle = lambda old, acc: F.lit((100 - damping) / 100) + F.lit(damping / 100) * F.coalesce(acc, F.lit(0.0))
        first = F.lit(float(init))
    return VertexProgram(name=f"pagerank-{arithmetic}", result=first, outgoing=lambda r: r, emit=emit, fold=SUM, settle=settle, wake=wake, reads_result=False)


def with_degrees(g: PropertyGraph) -> DataFrame:
    """Edges with their source's out-degree: computed once, used by every iteration."""
    degrees = g.out_degrees().select(F.col("id").alias("src"), F.col("out_degree").alias("_degree"))
    return g.edges.select("src", "dst").join(degrees, "src")


def pagerank_run(g: PropertyGraph, iterations: int = 10, arithmetic: str = "double", strategy: Strategy = flat, damping: int = 85, wake: str = ALL, init: float = 1.0, on_step=None, write_every: int | None = None) -> RunResult:
    """Run and keep the trace. State is written every 5 steps where a step reads it once, else every step.

    The graph's tables are written once, so that whatever they are derived from is read once, not per step.
    """
    from ..runtime.scratch import drop, save

    own_layout = hasattr(strategy, "begin")
    write_every = write_every or (5 if strategy in (flat, no_premerge) or getattr(strategy, "reads_once", False) else 1)
    plain = save(g.edges.select("src", "dst"), "edges")
    vertices = save(g.vertices.select("id"), "vertices")
    edges = with_degrees(PropertyGraph(vertices, plain))
    edges = edges if own_layout else PropertyGraph(vertices, edges).resident().edges
    try:
        return run(edges, vertices, rank_program(arithmetic, damping, wake, init), iterations, strategy, on_step=on_step, fixed=True, write_every=write_every)
    finally:
        if not own_layout:
            edges.unpersist()
        drop(g.spark, plain, vertices)


def pagerank(g: PropertyGraph, iterations: int = 10, **options) -> DataFrame:
    """(id, result) after ``iterations``; dangling mass is dropped, as the formula implies."""
    return pagerank_run(g, iterations, **options).frame


def pagerank_until(g: PropertyGraph, tol: float = 1e-6, max_steps: int = 100, dangling: str = "drop", sources: DataFrame | None = None, weight: str | None = None, damping: float = 0.85) -> tuple[DataFrame, int]:
    """Rank in doubles until no vertex moves by ``tol``: options beyond the plain formula.

    ``dangling='redistribute'`` shares the rank of vertices without out-edges equally; ``sources`` (ids)
    restart only there; ``weight`` splits rank by an edge column.
    """
    from ..runtime.scratch import drop, save

    share = F.col(weight).cast("double") if weight else F.lit(1.0)
    totals = g.edges.groupBy("src").agg(F.sum(share).alias("_t"))
    edges = g.edges.select("src", "dst", share.alias("_s")).join(totals, "src").select("src", "dst", (F.col("_s") / F.col("_t")).alias("_p")).persist()
    vertices = save(g.vertices.select("id").join(totals.select(F.col("src").alias("id"), F.lit(False).alias("_dangling")), "id", "left").fillna(True), "vertices")
    n = vertices.count()
    if sources is None:
        base = vertices.withColumn("_base", F.lit(1 - damping))
    else:
        chosen = sources.select("id", F.lit(True).alias("_chosen")).distinct()
        base = vertices.join(chosen, "id", "left").withColumn("_base", F.when(F.col("_chosen"), F.lit((1 - damping) * n / max(1, sources.distinct().count()))).otherwise(0.0)).drop("_chosen")
    state, step = save(base.withColumn("rank", F.lit(1.0)), "rank"), 0
    while step < max_steps:
        acc = edges.join(state.select(F.col("id").alias("src"), "rank"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("rank") * F.col("_p")).alias("acc"))
        spare = 0.0
        if dangling == "redistribute":
            spare = (state.where("_dangling").agg(F.sum("rank")).first()[0] or 0.0) / n
        new = F.col("_base") + damping * (F.coalesce("acc", F.lit(0.0)) + spare)
        after = save(state.join(acc, "id", "left").select("id", "_dangling", "_base", new.alias("rank"), F.abs(new - F.col("rank")).alias("_move")), "rank")
        moved = after.agg(F.max("_move")).first()[0] or 0.0
        drop(edges.sparkSession, state)
        state, step = after, step + 1
        if moved < tol:
            break
    edges.unpersist()
    return state.select("id", F.col("rank").alias("result")), step
