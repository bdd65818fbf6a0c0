"""Snapshots every n steps: homes' state and activity only; proxies and messages are derived again."""

from __future__ import annotations

import hashlib
import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class Checkpointer:
    """Writes <path>/step-<n> and a manifest row per snapshot; use ``checkpointer`` as ``on_step``."""

    def __init__(self, spark: SparkSession, path: str, program: str, every: int = 2):
        self.spark, self.path, self.program, self.every = spark, path.rstrip("/"), program, every

    @staticmethod
    def schema_hash(state: DataFrame) -> str:
        return hashlib.sha256(json.dumps(state.schema.jsonValue(), sort_keys=True).encode()).hexdigest()[:16]

    def __call__(self, step: int, state: DataFrame) -> None:
        if step % self.every:
            return
        where = f"{self.path}/step-{step}"
        state.write.mode("overwrite").parquet(where)
        row = [(step, where, state.count(), self.program, self.schema_hash(state))]
        manifest = self.spark.createDataFrame(row, "step int, path string, rows long, program string, schema_hash string")
        manifest.coalesce(1).write.mode("append").json(f"{self.path}/manifest")

    def manifest(self) -> DataFrame:
        return self.spark.read.schema("step int, path string, rows long, program string, schema_hash string").json(f"{self.path}/manifest")

    def resume(self) -> tuple[int, DataFrame]:
        """(step, state) of the latest snapshot; refuses one that doesn't fit its manifest row."""
        row = self.manifest().orderBy(F.desc("step")).first()
        if row is None:
            raise ValueError("no snapshot")
        state = self.spark.read.parquet(row["path"])
        if row["program"] != self.program or row["schema_hash"] != self.schema_hash(state) or row["rows"] != state.count():
            raise ValueError(f"snapshot of step {row['step']} does not fit its manifest")
        return row["step"], state


def checkpoint_stats(checkpointer: Checkpointer, failed_at: int) -> DataFrame:
    """(snapshots, rows, replayed): what recovery from a failure in step ``failed_at`` costs."""
    m = checkpointer.manifest().where(F.col("step") < failed_at)
    return m.agg(F.count("*").alias("snapshots"), F.coalesce(F.sum("rows"), F.lit(0)).alias("rows"), (failed_at - F.coalesce(F.max("step"), F.lit(0))).alias("replayed"))
