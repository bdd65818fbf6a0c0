"""Written intermediate tables in the folder that every executor shares.

Lineage is cut by writing a table and reading it back, so a lost executor costs a re-read and
never a recomputation of the whole history. The folder is the one named by the session in
``spark.checkpoint.dir``; a private one is made only where the session names none and runs on one machine
(tests, notebooks), because a machine-local folder is invisible to other machines.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Observation, SparkSession

_own_folder: str | None = None
#: Session setting, changeable at run time: whether a query's shuffle files go when the query ends.
RELEASE = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """Folder for intermediate tables: the session's checkpoint folder, or a temporary one if unset."""
    global _own_folder
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if _own_folder is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        _own_folder = "file://" + tempfile.mkdtemp(prefix="edgefold-")
    return _own_folder


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder; it is deleted when the session's JVM ends."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    return path


@contextmanager
def shuffles_released(spark: SparkSession) -> Iterator[None]:
    """Queries run within give up their shuffle files when they end, not when the driver next collects garbage.

    What a written table was made from is never read again. Should a frame be run twice all the same, or a lost block be
    made anew, the missing files are a fetch failure, and their stage runs again.
    """
    before = spark.conf.get(RELEASE, "false")
    spark.conf.set(RELEASE, "true")
    try:
        yield
    finally:
        spark.conf.set(RELEASE, before)


def save(df: DataFrame, name: str, observed: Observation | None = None, *figures: Column) -> DataFrame:
    """Write ``df`` to the shared folder and return a DataFrame that reads it back.

    ``figures`` are aggregates that ``observed`` has after the write, at no job of their own.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    with shuffles_released(spark):
        (df.observe(observed, *figures) if observed else df).write.option("compression", "zstd").parquet(path)
    written = spark.read.schema(df.schema).parquet(path)
    written._scratch_path = path
    return written


def read_all(frames: list[DataFrame]) -> DataFrame:
    """One DataFrame over the rows of frames of equal columns made by :func:`save`; a single scan, however many they are."""
    return frames[0].sparkSession.read.schema(frames[0].schema).parquet(*(vars(f)["_scratch_path"] for f in frames))


def drop(spark: SparkSession, *frames: DataFrame) -> None:
    """Delete the files behind frames made by :func:`save` once nothing needs them."""
    jvm = spark.sparkContext._jvm
    for frame in frames:
        if path := vars(frame).get("_scratch_path"):
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
