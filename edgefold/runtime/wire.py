"""Cost models of the reference's buffers and memory, as arithmetic over counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..proxy.graph import ProxyGraph

HEADER = 8


def wire_bytes(pg: ProxyGraph, payload: int = 8, capacity: int = 65536) -> DataFrame:
    """(pairs, messages, buffers, bytes) of a step in which all emit.

    Per ordered pair of parts, messages of 8 + ``payload`` bytes fill buffers of ``capacity`` bytes with
    an 8-byte header each.
    """
    per = (capacity - HEADER) // (8 + payload)
    pairs = pg.proxy_edges().groupBy("from_pid", "to_pid", "role").agg(F.count("*").alias("n"))
    buffers = F.ceil(F.col("n") / per)
    return pairs.agg(
        F.count("*").alias("pairs"),
        F.sum("n").cast("long").alias("messages"),
        F.sum(buffers).cast("long").alias("buffers"),
        F.sum(buffers * HEADER + F.col("n") * (8 + payload)).cast("long").alias("bytes"),
    )


def topology_bytes(pg: ProxyGraph) -> DataFrame:
    """(local_ids, edges, bytes, gas_bytes): compressed rows with 32-bit local ids against a split-phase engine.

    The one-sided engine keeps an offset of 8 bytes per local vertex and 4 bytes per edge, once. A
    split-phase engine keeps in- and out-edges and 8 bytes of state on each edge.
    """
    local = pg.rows().agg(F.count("*").alias("local_ids"))
    edges = pg.edges.agg(F.count("*").alias("edges"))
    n, e = F.col("local_ids"), F.col("edges")
    return local.crossJoin(edges).select("local_ids", "edges", (8 * n + 4 * e).alias("bytes"), (2 * (8 * n + 4 * e) + 8 * e).alias("gas_bytes"))


def capacity_gigabytes(vertices: float, edges: float, replicas: float = 2.5, state: int = 24, split_phase: bool = False) -> float:
    """Memory of a run in GB: topology once or twice, state per local vertex, values on edges if split."""
    local = vertices * replicas
    one = 8 * local + 4 * edges + state * local
    return (2 * one + 16 * edges if split_phase else one) / 1e9
