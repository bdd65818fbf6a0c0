"""Readers and writers of edge lists, graphs and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import PropertyGraph

EDGE_SCHEMA = "src long, dst long, w long"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE_SCHEMA) -> DataFrame:
    """Edge list from csv, tsv, text (white space, # comments), json, orc or parquet, with a stated schema."""
    if fmt in ("csv", "tsv"):
        return spark.read.schema(schema).option("sep", "," if fmt == "csv" else "\t").option("comment", "#").csv(path)
    if fmt == "text":
        names = [c.split()[0] for c in schema.split(",")]
        kinds = [c.split()[1] for c in schema.split(",")]
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.col("value").startswith("#") & (F.trim("value") != ""))
        return lines.select(*(F.get(parts, F.lit(i)).cast(k).alias(n) for i, (n, k) in enumerate(zip(names, kinds))))
    return spark.read.schema(schema).format(fmt).load(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    if fmt == "tsv":
        edges.write.option("sep", "\t").csv(path)
    elif fmt == "text":
        edges.select(F.concat_ws(" ", *edges.columns).alias("value")).write.text(path)
    else:
        edges.write.format(fmt).save(path)


def save_graph(g: PropertyGraph, path: str, layout: str = "plain", parts: int = 16) -> None:
    """Write a graph: ``plain`` files sorted by source, ``by_part`` one folder per part, ``bucketed`` a table named ``path``.

    Sorting by source gives row groups narrow source ranges, so a frontier skips most of them.
    """
    if layout == "bucketed":
        g.edges.write.bucketBy(parts, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(f"{path}_edges")
        g.vertices.write.bucketBy(parts, "id").sortBy("id").mode("overwrite").saveAsTable(f"{path}_vertices")
        return
    g.vertices.write.parquet(f"{path}/vertices")
    if layout == "by_part":
        g.edges.repartition("pid").sortWithinPartitions("pid", "src", "dst").write.partitionBy("pid").parquet(f"{path}/edges")
    else:
        g.edges.repartitionByRange(parts, "src").sortWithinPartitions("src", "dst").write.parquet(f"{path}/edges")


def load_graph(spark: SparkSession, path: str, layout: str = "plain") -> PropertyGraph:
    if layout == "bucketed":
        return PropertyGraph(spark.table(f"{path}_vertices"), spark.table(f"{path}_edges"))
    return PropertyGraph(spark.read.parquet(f"{path}/vertices"), spark.read.parquet(f"{path}/edges"))


RMAT_BLOCK = 1 << 16


def rmat_format(spark: SparkSession) -> str:
    """Register the generator as a batch source ``rmat`` with options scale, edge_factor, seed, parts and blocks.

    ``blocks`` (comma-separated) are blocks of ``RMAT_BLOCK`` edge numbers to draw instead of the first 2^scale * edge_factor.
    """
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class RmatReader(DataSourceReader):
        def __init__(self, options):
            self.scale, self.factor = int(options.get("scale", 8)), int(options.get("edge_factor", 16))
            self.seed, self.parts = int(options.get("seed", 1)), int(options.get("parts", 4))
            self.blocks = [int(b) for b in options["blocks"].split(",") if b] if "blocks" in options else None

        def partitions(self):
            if self.blocks is not None:
                return [InputPartition((b * RMAT_BLOCK, (b + 1) * RMAT_BLOCK)) for b in self.blocks]
            total = (1 << self.scale) * self.factor
            return [InputPartition((total * i // self.parts, total * (i + 1) // self.parts)) for i in range(self.parts)]

        def read(self, partition):
            import hashlib

            import numpy as np
            import pyarrow as pa

            a, b, c = 57, 19, 19
            first, end = partition.value
            for low in range(first, end, 16_384):
                numbers = range(low, min(low + 16_384, end))
                src = dst = np.zeros(len(numbers), dtype=np.int64)
                for level in range(self.scale):
                    if level % 4 == 0:  # a digest is four numbers of eight hex digits
                        digests = b"".join(hashlib.md5(f"{self.seed}:{i}:{level // 4}".encode()).digest() for i in numbers)
                        draws = np.frombuffer(digests, dtype=">u4").reshape(-1, 4) % 100
                    draw = draws[:, level % 4]
                    src = src * 2 + (draw >= a + b)
                    dst = dst * 2 + (((draw >= a) & (draw < a + b)) | (draw >= a + b + c))
                yield pa.RecordBatch.from_arrays([pa.array(numbers, pa.int64()), pa.array(src), pa.array(dst)], ["edge_seq", "src", "dst"])

    class RmatSource(DataSource):
        @classmethod
        def name(cls):
            return "rmat"

        def schema(self):
            return "edge_seq long, src long, dst long"

        def reader(self, schema):
            return RmatReader(self.options)

    spark.dataSource.register(RmatSource)
    return "rmat"
