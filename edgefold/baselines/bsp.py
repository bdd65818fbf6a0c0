"""Message-passing super-steps: messages of one step are written, and read in the next.

With a merger, messages from one task to one vertex are merged before they are written.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..model.program import ALL, VertexProgram, seed
from ..model.superstep import messages, settled
from ..runtime.scratch import drop, save


def run_bsp(edges: DataFrame, vertices: DataFrame, program: VertexProgram, max_steps: int | None = None, merger: bool = False) -> tuple[DataFrame, int, list[int]]:
    """((id, result), steps, messages stored per step)."""
    spark = edges.sparkSession
    waiting, seen = F.count_if("can_emit").alias("waiting"), Observation()
    state, step, stored = save(seed(vertices, program), "state", seen, waiting), 0, []
    while max_steps is None or step < max_steps:
        if program.wake != ALL and seen.get["waiting"] == 0:
            break
        frontier = state.where("can_emit")
        sent = messages(edges, frontier, program).select("dst", "payload")
        if merger:
            sent = sent.groupBy("dst").agg(program.fold.aggregate(F.col("payload")).alias("payload"))
        written, seen = Observation(), Observation()
        inbox = save(sent, "inbox", written, F.count("*").alias("n"))
        stored.append(written.get["n"])
        acc = inbox.groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("payload")).alias("acc"))
        after = save(settled(state, acc, program), "state", seen, waiting)
        drop(spark, inbox, state)
        state, step = after, step + 1
    return state.select("id", "result"), step, stored
