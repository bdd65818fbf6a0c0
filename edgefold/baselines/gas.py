"""Gather-apply-scatter: vertices poll all their in-edges for values that an earlier phase stored there.

Every step reads each in-edge of a woken vertex and writes each out-edge of a changed one, so an edge is
touched twice and its value is kept from one step to the next. Results equal the one-sided engine's.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..model.program import ALL, VertexProgram, seed
from ..runtime.scratch import drop, save


@dataclass
class GasResult:
    frame: DataFrame
    steps: int
    gathered: list[int] = field(default_factory=list)
    stored: list[int] = field(default_factory=list)

    @property
    def touches(self) -> int:
        return sum(self.gathered) + sum(self.stored)


def scatter(edges: DataFrame, state: DataFrame, program: VertexProgram) -> DataFrame:
    """Edges with the value of emitting sources stored on them and a signal for their target."""
    sources = state.where("can_emit").select(F.col("id").alias("src"), F.col("outgoing").alias("_out"), F.lit(True).alias("_now"))
    joined = edges.join(sources, "src", "left")
    fresh = F.when(F.col("_now"), program.emit(F.col("_out"), F.col))
    kept = F.coalesce(fresh, F.col("stored")) if "stored" in edges.columns else fresh
    return joined.withColumn("_s", kept).withColumn("signal", F.coalesce("_now", F.lit(False))).drop("_out", "_now", "stored").withColumnRenamed("_s", "stored")


def gather(edges: DataFrame, program: VertexProgram, every: bool) -> DataFrame:
    """(id, acc) from all in-edges of woken vertices, signalled now or holding an older value."""
    woken = edges.where("signal").select("dst").distinct()
    polled = edges if every else edges.join(woken, "dst", "left_semi")
    return polled.where("stored IS NOT NULL").groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("stored")).alias("acc"))


def run_gas(edges: DataFrame, vertices: DataFrame, program: VertexProgram, max_steps: int | None = None, counted: bool = True) -> GasResult:
    """Run a program phase by phase; ``counted`` records polled and stored edges per step."""
    from ..model.superstep import settled

    program.validate()
    spark = edges.sparkSession
    seen = Observation()
    state, out, step = save(seed(vertices, program), "state", seen, F.count_if("can_emit").alias("waiting")), GasResult(vertices, 0), 0
    current = edges
    while max_steps is None or step < max_steps:
        if program.wake != ALL and seen.get["waiting"] == 0:
            break
        after = save(scatter(current, state, program), "edge-state")
        if counted:
            signalled = after.where("signal")
            polled = after if program.wake == ALL else after.join(signalled.select("dst").distinct(), "dst", "left_semi")
            out.stored.append(signalled.count()), out.gathered.append(polled.count())
        seen = Observation()
        new = save(settled(state, gather(after, program, program.wake == ALL), program), "state", seen, F.count_if("can_emit").alias("waiting"))
        if step:
            drop(spark, current)
        drop(spark, state)
        current, state, step = after, new, step + 1
    out.frame, out.steps = state.select("id", "result"), step
    return out
