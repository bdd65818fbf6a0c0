"""Edge-cut placements of vertices: hash, range, and published streaming heuristics."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graph.ids import mix
from ..graph.model import PropertyGraph
from .hashing import hash_homes


def vertex_partition(g: PropertyGraph, k: int, method: str = "hash", loaders: int = 1, gamma: float = 1.5) -> DataFrame:
    """(id, home) by ``hash``, ``range``, ``chunk``, ``balanced``, ``ldg`` or ``fennel``.

    ``range`` cuts the sorted ids into k runs by approximate quantiles; ``chunk`` and ``balanced`` fill
    parts one after the other or in turn; ``ldg`` prefers the part with most neighbours, weighted by
    free room; ``fennel`` subtracts a power of the load instead. Streams are dealt to ``loaders``.
    """
    if method == "hash":
        return hash_homes(g.vertices, k)
    if method == "range":
        cuts = g.vertices.stat.approxQuantile("id", [i / k for i in range(1, k)], 0.001) if k > 1 else []
        home = sum(((F.col("id") > c).cast("int") for c in cuts), F.lit(0))
        return g.vertices.select("id", home.cast("int").alias("home"))
    if method in ("chunk", "balanced"):
        stream = Window.partitionBy("l").orderBy("_k", "id")
        dealt = g.vertices.select("id", mix("id").alias("_k")).withColumn("l", (F.col("_k") % loaders).cast("int"))
        numbered = dealt.select("id", "l", (F.row_number().over(stream) - 1).alias("n"), F.count("*").over(Window.partitionBy("l")).alias("of"))
        home = F.col("n") % k if method == "balanced" else F.least(F.expr(f"(n * {k}) div of"), F.lit(k - 1))
        return numbered.select("id", home.cast("int").alias("home"))
    both = g.symmetrize().edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_set("dst")).alias("around"))
    rows = g.vertices.select("id").join(both, "id", "left").withColumn("_k", mix("id")).withColumn("l", (F.col("_k") % loaders).cast("int"))
    n, m = g.vertices.count(), g.edges.count()
    room, alpha = max(1.0, n / loaders / k), m * k ** (gamma - 1) / max(1, n) ** gamma

    def place(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["_k", "id"])
        home, load, out = {}, np.zeros(k), []
        for v, around in zip(frame["id"].tolist(), frame["around"]):
            near = np.zeros(k)
            for u in around if around is not None else ():
                if u in home:
                    near[home[u]] += 1
            score = near * (1 - load / (room * 1.1)) if method == "ldg" else near - alpha * gamma * load ** (gamma - 1)
            best = int(np.lexsort((np.arange(k), load, -score))[0])
            home[v], load[best] = best, load[best] + 1
            out.append(best)
        return pd.DataFrame({"id": frame["id"].to_numpy(), "home": np.array(out, dtype=np.int32)})

    return rows.groupBy("l").applyInPandas(place, "id long, home int")
