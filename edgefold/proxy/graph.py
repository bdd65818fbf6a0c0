"""Homes and proxies of a placed graph.

An in-proxy collects messages for a remote home in the part where edges to it lie; an out-proxy relays a
remote home's value to edges from it placed here. Neither holds the home's state, so each is used in one
direction only. A mirror of the vertex-cut comparator holds a whole copy and is synchronised both ways.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph.ids import mix


def pick_homes(placed: DataFrame, vertices: DataFrame, k: int, home: str = "majority") -> DataFrame:
    """(id, home): the part with most of a vertex's edges (ties to the lowest), or the scramble of its id.

    Vertices without edges always take the scramble.
    """
    hashed = vertices.select("id", (mix("id") % k).cast("int").alias("_hash"))
    if home == "hash":
        return hashed.withColumnRenamed("_hash", "home")
    ends = placed.select(F.col("src").alias("id"), "pid").unionByName(placed.select(F.col("dst").alias("id"), "pid"))
    most = ends.groupBy("id", "pid").agg(F.count("*").alias("n")).groupBy("id").agg(F.max_by("pid", F.struct("n", -F.col("pid"))).alias("_most"))
    return hashed.join(most, "id", "left").select("id", F.coalesce("_most", "_hash").cast("int").alias("home"))


@dataclass(frozen=True)
class ProxyGraph:
    """A placed graph: edges (src, dst, pid), homes (id, home) and proxies (pid, id, role)."""

    edges: DataFrame
    homes: DataFrame
    proxies: DataFrame

    @staticmethod
    def from_assignment(placed: DataFrame, homes: DataFrame) -> "ProxyGraph":
        """Derive the proxies of a placement; an edge on a third part links an out-proxy to an in-proxy."""
        edges = placed.select("src", "dst", F.col("pid").cast("int").alias("pid"))

        def away(end: str, role: str) -> DataFrame:
            there = edges.select("pid", F.col(end).alias("id")).distinct().join(homes, "id").where("pid <> home")
            return there.select("pid", "id", F.lit(role).alias("role"))

        return ProxyGraph(edges, homes, away("src", "out").unionByName(away("dst", "in")))

    @staticmethod
    def from_mirrors(edges: DataFrame, homes: DataFrame, mirrors: DataFrame) -> "ProxyGraph":
        """Split each mirror (pid, id) into an out-proxy if its part holds out-edges, an in-proxy if in-edges."""
        made = ProxyGraph.from_assignment(edges, homes)
        kept = made.proxies.join(mirrors.select("pid", "id"), ["pid", "id"], "left_semi")
        return ProxyGraph(made.edges, homes, kept)

    def rows(self) -> DataFrame:
        """(pid, id, role) with roles home, in and out."""
        return self.homes.select(F.col("home").alias("pid"), "id", F.lit("home").alias("role")).unionByName(self.proxies)

    def proxy_edges(self) -> DataFrame:
        """(id, from_pid, to_pid, role): home to out-proxy, in-proxy to home."""
        at = self.proxies.join(self.homes, "id")
        out = F.col("role") == "out"
        return at.select("id", F.when(out, F.col("home")).otherwise(F.col("pid")).alias("from_pid"), F.when(out, F.col("pid")).otherwise(F.col("home")).alias("to_pid"), "role")

    def routing(self) -> DataFrame:
        """(id, parts): where a home's value goes each step."""
        out = self.proxies.where("role = 'out'")
        return out.groupBy("id").agg(F.sort_array(F.collect_set("pid")).alias("parts"))

    def mirrors(self) -> DataFrame:
        """(pid, id) of the vertex-cut comparator on the same placement: both ends, homes left out."""
        return self.proxies.select("pid", "id").distinct()

    def localize(self) -> DataFrame:
        """(pid, lid, id, role): homes numbered from 0 in id order, then proxies. 32 bits per part."""
        rank = F.when(F.col("role") == "home", 0).when(F.col("role") == "in", 1).otherwise(2)
        here = Window.partitionBy("pid").orderBy(rank, "id")
        return self.rows().select("pid", (F.row_number().over(here) - 1).cast("int").alias("lid"), "id", "role")

    def to_csr(self) -> DataFrame:
        """(pid, lid, offset, degree, targets): compressed rows of each part's edges over local numbers.

        A source is its home's number where it lives, else its out-proxy's; a target likewise with in-proxies.
        """
        local = self.localize()

        def named(end: str, role: str) -> DataFrame:
            return local.where(F.col("role").isin("home", role)).select("pid", F.col("id").alias(end), F.col("lid").alias(f"l{end}"))

        edges = self.edges.join(named("src", "out"), ["pid", "src"]).join(named("dst", "in"), ["pid", "dst"])
        lists = edges.groupBy("pid", "lsrc").agg(F.sort_array(F.collect_list("ldst")).alias("targets"))
        ahead = Window.partitionBy("pid").orderBy("lsrc").rowsBetween(Window.unboundedPreceding, -1)
        offset = F.coalesce(F.sum(F.size("targets")).over(ahead), F.lit(0)).cast("long")
        return lists.select("pid", F.col("lsrc").alias("lid"), offset.alias("offset"), F.size("targets").alias("degree"), "targets")

    def violations(self) -> DataFrame:
        """One row (n): homes that aren't unique plus in-proxies that have an out-edge in their part."""
        twice = self.homes.groupBy("id").count().where("count > 1").select("id")
        ins = self.proxies.where("role = 'in'").select("pid", F.col("id").alias("src"))
        outs = self.proxies.where("role = 'out'").select("pid", F.col("id").alias("src"))
        backward = self.edges.join(ins, ["pid", "src"], "left_semi").join(outs, ["pid", "src"], "left_anti")
        return twice.select(F.lit(1).alias("n")).unionByName(backward.select(F.lit(1).alias("n"))).agg(F.count("*").alias("n"))
