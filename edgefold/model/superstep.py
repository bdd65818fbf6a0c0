"""The bulk-synchronous loop: emit along out-edges, fold at targets, settle, retire.

A step is one join of the frontier to the edges and one aggregation by target, whose partial half runs
in the task that made the messages; no message is ever stored. State is written to the shared folder
after a step, so plans stay short and a lost executor costs one read. The driver learns one number per
step: how many vertices emit next.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..runtime.scratch import drop, save
from .algebra import allow_premerge
from .program import ALL, VertexProgram, seed

#: A strategy turns (edges, frontier, program) into (id, acc). One with ``begin(edges)`` and ``end()`` lays edges out once a run.
Strategy = Callable[[DataFrame, DataFrame, VertexProgram], DataFrame]


@dataclass
class RunResult:
    """Final state, steps run, emitting vertices before each step, seconds of each, and the edges."""

    state: DataFrame
    steps: int
    frontier: list[int] = field(default_factory=list)
    timings: list[float] = field(default_factory=list)
    edges: DataFrame | None = None

    @property
    def frame(self) -> DataFrame:
        return self.state.select("id", "result")


def messages(edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
    """(dst, payload) of every out-edge of the frontier that carries a message."""
    used = edges.where(program.emit_where) if program.emit_where else edges
    joined = used.join(frontier.select(F.col("id").alias("src"), F.col("outgoing").alias("_out")), "src")
    sent = joined.select("src", "dst", program.emit(F.col("_out"), F.col).alias("payload"))
    return sent.where("payload IS NOT NULL")


def flat(edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
    """Messages fold by target; the engine's partial aggregation merges them where they are made."""
    sent = messages(edges, frontier, program)
    if not allow_premerge(program.fold):
        return no_premerge(edges, frontier, program)
    return sent.groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("payload")).alias("acc"))


def no_premerge(edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
    """Ablation: every message crosses to its target's task on its own and folds only there."""
    sent = messages(edges, frontier, program)
    n = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grouped = sent.repartition(n, "dst").groupBy(F.col("dst").alias("id")).agg(F.collect_list("payload").alias("_all"))
    return grouped.select("id", program.fold.merge(F.col("_all")).alias("acc"))


def two_level(salts: int = 16) -> Strategy:
    """Fold by (target, salt of the source) and then by target, so a hub's messages spread over tasks."""

    def run(edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
        salted = messages(edges, frontier, program).withColumn("_salt", F.pmod(F.xxhash64("src"), F.lit(salts)))
        first = salted.groupBy("dst", "_salt").agg(program.fold.aggregate(F.col("payload")).alias("payload"))
        return first.groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("payload")).alias("acc"))

    return run


def targeted(edges: DataFrame, frontier: DataFrame, program: VertexProgram, state: DataFrame) -> DataFrame:
    """Messages whose function also reads the target's result: one more join, no proxies."""
    sent = messages(edges, frontier, program).join(state.select(F.col("id").alias("dst"), F.col("result").alias("_there")), "dst")
    made = sent.select("dst", program.needs_target(F.col("_there"), F.col("payload")).alias("payload"))
    return made.groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("payload")).alias("acc"))


def settled(state: DataFrame, acc: DataFrame, program: VertexProgram) -> DataFrame:
    """State after a step: woken vertices take their new result, all others pass through."""
    joined = state.join(acc, "id", "left")
    woken = F.lit(True) if program.wake == ALL else F.col("acc").isNotNull()
    new = F.when(woken, program.settle(F.col("result"), F.col("acc"))).otherwise(F.col("result"))
    stays = F.lit(False) if program.retire else F.col("can_emit")
    keep = joined.select("id", *program.attributes, F.col("result").alias("_old"), new.alias("result"), woken.alias("_woken"), stays.alias("_stays"))
    again = F.when(F.col("_woken"), program.rearm(F.col("_old"), F.col("result"))).otherwise(F.col("_stays"))
    return keep.select("id", *program.attributes, "result", program.outgoing(F.col("result")).alias("outgoing"), F.coalesce(again, F.lit(False)).alias("can_emit"))


def resettled(vertices: DataFrame, acc: DataFrame, program: VertexProgram) -> DataFrame:
    """State after a step in which every vertex settles from its messages alone and emits again.

    The old state isn't read, so a chain of such steps stays a chain and needs no table in between.
    """
    joined = vertices.join(acc, "id", "left")
    new = joined.select("id", *program.attributes, program.settle(F.lit(None), F.col("acc")).alias("result"))
    return new.select("id", *program.attributes, "result", program.outgoing(F.col("result")).alias("outgoing"), F.lit(True).alias("can_emit"))


def updated_edges(edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
    """Edges with the program's new values on the out-edges of the frontier."""
    joined = edges.join(frontier.select(F.col("id").alias("src"), F.col("outgoing").alias("_out"), F.lit(True).alias("_sent")), "src", "left")
    new = {c: F.when(F.col("_sent"), f(F.col("_out"), F.col)).otherwise(F.col(c)) for c, f in program.edge_update.items()}
    return joined.withColumns(new).drop("_out", "_sent")


def check_invariants(before: DataFrame, after: DataFrame, acc: DataFrame, program: VertexProgram) -> None:
    """Debug check of the phases: settling changes woken homes only, and every vertex stays exactly once.

    Accumulators start empty in each step and values being emitted can't change while they are, since a
    step reads one written state and writes another.
    """
    asleep = before.join(acc.select("id"), "id", "left_anti") if program.wake != ALL else before.limit(0)
    held = asleep.select("id", "result").exceptAll(after.select("id", "result")).limit(1).count()
    if held or after.select("id").exceptAll(before.select("id")).limit(1).count() or after.count() != before.count():
        raise AssertionError(f"{program.name}: a step changed vertices that got no message, or lost or made some")


def run(
    edges: DataFrame,
    vertices: DataFrame | None,
    program: VertexProgram,
    max_steps: int | None = None,
    strategy: Strategy = flat,
    state: DataFrame | None = None,
    on_step: Callable[[int, DataFrame], None] | None = None,
    fixed: bool = False,
    debug_invariants: bool = False,
    write_every: int = 1,
) -> RunResult:
    """Run until nobody emits or ``max_steps``; ``fixed`` skips the count when every vertex stays active.

    ``state`` resumes from a saved state. ``on_step`` sees every written state. With ``fixed``, programs that
    settle all vertices and don't read their old results may write their state every ``write_every`` steps
    only; a lost executor then costs that many steps at most.
    """
    program.validate(state)
    if hasattr(strategy, "begin"):
        strategy.begin(edges)
    try:
        return _loop(edges, vertices, program, max_steps, strategy, state, on_step, fixed, debug_invariants, write_every)
    finally:
        if hasattr(strategy, "end"):
            strategy.end()


def _loop(edges, vertices, program, max_steps, strategy, state, on_step, fixed, debug_invariants, write_every) -> RunResult:
    spark = edges.sparkSession
    chained = fixed and max_steps is not None and program.wake == ALL and not program.reads_result and not program.retire and not program.edge_update and not on_step and vertices is not None
    chained = chained and write_every > 1
    waiting = None
    if state is not None:
        current = state
    elif chained:  # the first chain starts from the seeds as they are computed
        current = seed(vertices, program)
    else:
        seen = Observation()
        current = save(seed(vertices, program), "state", seen, F.count_if("can_emit").alias("waiting"))
        waiting = seen.get["waiting"]
    result, step, owned = RunResult(current, 0, edges=edges), 0, state is None and not chained
    while max_steps is None or step < max_steps:
        began = time.time()
        if chained:
            n, after = min(write_every, max_steps - step), current
            static = vertices.select("id", *program.attributes)
            for _ in range(n):
                after = resettled(static, strategy(edges, after, program), program)
            after = save(after, "state")
            if owned:
                drop(spark, current)
            current, step, owned = after, step + n, True
            result.timings += [(time.time() - began) / n] * n
            continue
        frontier = current.where("can_emit")
        if not fixed:
            waiting = frontier.count() if waiting is None else waiting
            if waiting == 0:
                break
            result.frontier.append(waiting)
        acc = targeted(edges, frontier, program, current) if program.needs_target else strategy(edges, frontier, program)
        seen = Observation()
        after = save(settled(current, acc, program), "state", seen, F.count_if("can_emit").alias("waiting"))
        waiting = seen.get["waiting"]
        if debug_invariants:
            check_invariants(current, after, acc, program)
        if program.edge_update:
            edges = save(updated_edges(edges, frontier, program), "edges")
        if on_step:
            on_step(step + 1, after)
        if owned:
            drop(spark, current)
        current, step, owned = after, step + 1, True
        result.timings.append(time.time() - began)
    result.state, result.steps, result.edges = current, step, edges
    return result
