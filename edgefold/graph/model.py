"""Directed property graph over two DataFrames: vertices (id, ...) and edges (src, dst, ...)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PropertyGraph:
    """Every edge is directed; an undirected one is two. Property columns are read only where named."""

    vertices: DataFrame
    edges: DataFrame
    #: Whether there may be vertices without edges.
    lone: bool = True

    @staticmethod
    def from_edges(edges: DataFrame) -> "PropertyGraph":
        """Graph whose vertices are the ends of its edges."""
        ends = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id")))
        return PropertyGraph(ends.distinct(), edges, lone=False)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def out_edges(self, some: DataFrame) -> DataFrame:
        """Edges whose source is among the ids of ``some``."""
        return self.edges.join(some.select(F.col("id").alias("src")), "src", "left_semi")

    def in_edges(self, some: DataFrame) -> DataFrame:
        """Edges whose target is among the ids of ``some``."""
        return self.edges.join(some.select(F.col("id").alias("dst")), "dst", "left_semi")

    @staticmethod
    def sources(edges: DataFrame) -> DataFrame:
        return edges.select(F.col("src").alias("id")).distinct()

    @staticmethod
    def targets(edges: DataFrame) -> DataFrame:
        return edges.select(F.col("dst").alias("id")).distinct()

    def where_vertices(self, rule: str | Column) -> "PropertyGraph":
        """Keep vertices that fit the rule and the edges between them."""
        kept = self.vertices.where(rule)
        ids = kept.select("id")
        edges = self.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
        return PropertyGraph(kept, edges)

    def where_edges(self, rule: str | Column) -> "PropertyGraph":
        """Keep edges that fit the rule, and all vertices."""
        return PropertyGraph(self.vertices, self.edges.where(rule))

    def transpose(self) -> "PropertyGraph":
        turned = [F.col("dst").alias("src"), F.col("src").alias("dst"), *(c for c in self.edges.columns if c not in ("src", "dst"))]
        return PropertyGraph(self.vertices, self.edges.select(*turned), self.lone)

    def symmetrize(self) -> "PropertyGraph":
        """Both directions of every edge, once each, without loops and properties."""
        plain = self.edges.select("src", "dst").where("src <> dst")
        both = plain.unionByName(plain.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        return PropertyGraph(self.vertices, both.distinct())

    def with_properties(self, table: DataFrame, *columns: str, on: str = "id") -> "PropertyGraph":
        """Vertices with columns of ``table`` joined on by id."""
        chosen = table.select(F.col(on).alias("id"), *columns)
        return PropertyGraph(self.vertices.join(chosen, "id", "left"), self.edges)

    def out_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out_degree"))

    def in_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_degree"))

    def resident(self, key: str = "src", partitions: int | None = None) -> "PropertyGraph":
        """Edges dealt and sorted by ``key`` and kept, so that each super-step neither moves nor sorts them."""
        n = partitions or int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        return PropertyGraph(self.vertices, self.edges.repartition(n, key).sortWithinPartitions(key).persist())

    def register(self, name: str) -> None:
        """Temporary views <name>_vertices and <name>_edges for SQL."""
        self.vertices.createOrReplaceTempView(f"{name}_vertices")
        self.edges.createOrReplaceTempView(f"{name}_edges")
