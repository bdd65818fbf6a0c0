"""Graphs that grow: placement of a stream of edges, and components kept up to date."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..algorithms.contract import contract_components
from ..graph.ids import mix
from ..partition.greedy import SharedTables
from ..runtime.scratch import new_path, save


class PlacedStream:
    """Greedy placement of a stream of edges: a micro-batch is a round of coordinated loaders.

    State is the loaders' shared presence, one row per vertex, joined to the ids that a batch names; a batch costs
    its own edges and one merge of the presence, never a loader's whole tables as one value.
    """

    def __init__(self, k: int, loaders: int = 4, directed: bool = True) -> None:
        self.k, self.loaders, self.directed = k, loaders, directed
        self.tables: SharedTables | None = None

    def add(self, batch: DataFrame) -> None:
        if self.tables is None:
            self.tables = SharedTables(batch.sparkSession, self.k, self.directed, loaders=self.loaders)
        dealt = batch.select("src", "dst").withColumn("loader", (mix("dst") % self.loaders).cast("int"))
        here = Window.partitionBy("loader").orderBy("src", "dst")
        self.tables.place(dealt.select((F.row_number().over(here) - 1).cast("long").alias("edge_seq"), "src", "dst", "loader"))

    def follow(self, stream: DataFrame) -> DataFrame:
        """Drain a stream of edges and return (src, dst, loader, pid)."""
        query = stream.writeStream.foreachBatch(lambda batch, _: self.add(batch)).option("checkpointLocation", new_path(stream.sparkSession, "marks")).trigger(availableNow=True).start()
        query.awaitTermination()
        if self.tables is None:  # a stream without rows has no batch
            return stream.sparkSession.createDataFrame([], "src long, dst long, loader int, pid int")
        return self.tables.frame().select("src", "dst", "loader", "pid")


class GrowingComponents:
    """Components of all edges so far: a batch adds its edges to the labels' star forest and contracts both.

    The forest has one edge per vertex, so a batch costs its own size plus the vertices', never all edges.
    """

    def __init__(self) -> None:
        self.labels: DataFrame | None = None

    def add(self, batch: DataFrame) -> None:
        edges = batch.select("src", "dst")
        if self.labels is not None:
            edges = edges.unionByName(self.labels.select(F.col("id").alias("src"), F.col("label").alias("dst")))
        self.labels = save(contract_components(edges), "labels")

    def follow(self, stream: DataFrame) -> DataFrame:
        """Drain a stream of edges and return (id, label)."""
        query = stream.writeStream.foreachBatch(lambda batch, _: self.add(batch)).option("checkpointLocation", new_path(stream.sparkSession, "marks")).trigger(availableNow=True).start()
        query.awaitTermination()
        return self.labels
