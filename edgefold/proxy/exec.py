"""Super-steps over a proxy graph or a mirror placement, with the messages each direction counted.

Edges stay in their parts: a strategy lays them out once per run, with their columns, by part and source, and a
step moves values and merged messages only. A home's value goes once to every part that has out-edges of it;
edges there emit; messages merge where they are made; merged messages go to their homes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.program import VertexProgram
from .graph import ProxyGraph


def emitted(edges: DataFrame, values: DataFrame, program: VertexProgram) -> DataFrame:
    """(pid, dst, payload) of a placed edge list whose sources' values are (pid, src, _out)."""
    used = edges.where(program.emit_where) if program.emit_where else edges
    return used.join(values, ["pid", "src"]).select("pid", "src", "dst", program.emit(F.col("_out"), F.col).alias("payload")).where("payload IS NOT NULL")


class Resident:
    """Placed edges and the parts that each source's value goes to, both laid out once for all steps of a run.

    An edge update changes columns that a layout holds, so it isn't offered here.
    """

    #: A step reads the state once, so several may run before it is written.
    reads_once = True

    def __init__(self, pg: ProxyGraph, placed: DataFrame | None = None):
        self.pg, self.placed = pg, placed
        self.edges = self.routes = None

    def targets(self) -> DataFrame:
        """(id, pid) of every part that gets a value of a vertex."""
        raise NotImplementedError

    def begin(self, edges: DataFrame) -> None:
        n = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        own = (self.placed if self.placed is not None else self.pg.edges).drop(*[c for c in edges.columns if c not in ("src", "dst")])
        full = own.join(edges, ["src", "dst"]) if set(edges.columns) - {"src", "dst"} else own
        self.edges = full.repartition(n, "pid", "src").sortWithinPartitions("pid", "src").persist()
        self.routes = self.targets().repartition(n, "id").sortWithinPartitions("id").persist()

    def end(self) -> None:
        for kept in (self.edges, self.routes):
            kept.unpersist()
        self.edges = self.routes = None

    def values(self, frontier: DataFrame) -> DataFrame:
        """(pid, src, _out): emitting vertices' values in the parts they go to."""
        return self.routes.join(frontier.select("id", "outgoing"), "id").select("pid", F.col("id").alias("src"), F.col("outgoing").alias("_out"))

    def __call__(self, edges: DataFrame, frontier: DataFrame, program: VertexProgram) -> DataFrame:
        if program.edge_update:
            raise ValueError("edges that stay in their parts can't be rewritten by a program")
        if self.edges is None:  # a single step outside a run
            self.begin(edges)
        return self.step(frontier, program)

    def step(self, frontier: DataFrame, program: VertexProgram) -> DataFrame:
        raise NotImplementedError


class Proxied(Resident):
    """One direction per proxy: values to out-proxies, merged messages from in-proxies."""

    def targets(self) -> DataFrame:
        outs = self.pg.proxies.where("role = 'out'").select("id", "pid")
        sources = self.pg.edges.select("pid", F.col("src").alias("id")).distinct()
        at_home = self.pg.homes.select("id", F.col("home").alias("pid")).join(sources, ["id", "pid"], "left_semi")
        return at_home.unionByName(outs)

    def step(self, frontier: DataFrame, program: VertexProgram) -> DataFrame:
        sent = emitted(self.edges, self.values(frontier), program)
        return sent.groupBy(F.col("dst").alias("id")).agg(program.fold.aggregate(F.col("payload")).alias("acc"))


class Mirrored(Resident):
    """Vertex-cut comparator: every replica gets the value, and every replica's sum goes to its home."""

    def targets(self) -> DataFrame:
        return self.pg.homes.select("id", F.col("home").alias("pid")).unionByName(self.pg.mirrors().select("id", "pid"))

    def step(self, frontier: DataFrame, program: VertexProgram) -> DataFrame:
        partial = emitted(self.edges, self.values(frontier), program).groupBy("pid", "dst").agg(program.fold.aggregate(F.col("payload")).alias("payload"))
        synced = self.routes.join(partial.withColumnRenamed("dst", "id"), ["pid", "id"])
        return synced.groupBy("id").agg(program.fold.aggregate(F.col("payload")).alias("acc"))


def proxied(pg: ProxyGraph, placed: DataFrame | None = None) -> Proxied:
    """Strategy that runs over ``pg``; ``placed`` adds edge columns to its (pid, src, dst)."""
    return Proxied(pg, placed)


def mirrored(pg: ProxyGraph) -> Mirrored:
    return Mirrored(pg)


def message_counts(pg: ProxyGraph, frontier: DataFrame) -> DataFrame:
    """(emitted, local_msgs, s_msgs, c_msgs) of one step from the emitting ids in ``frontier``.

    ``emitted`` is one per out-edge; ``s_msgs`` cross from homes to out-proxies; ``c_msgs`` cross from
    in-proxies to homes after merging; ``local_msgs`` is what merges within the home's part.
    """
    ids = frontier.select("id")
    live = pg.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi")
    s = pg.proxies.where("role = 'out'").join(ids, "id", "left_semi").agg(F.count("*").alias("s_msgs"))
    at = live.join(pg.homes.select(F.col("id").alias("dst"), "home"), "dst")
    merged = at.groupBy("pid", "dst", "home").agg(F.count("*").alias("n"))
    counts = merged.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("emitted"),
        F.coalesce(F.sum(F.when(F.col("pid") == F.col("home"), F.col("n"))), F.lit(0)).alias("local_msgs"),
        F.count_if(F.col("pid") != F.col("home")).alias("c_msgs"),
    )
    return counts.crossJoin(s).select("emitted", "local_msgs", "s_msgs", "c_msgs")
