"""Multi-stage algorithms: strong components, betweenness, bipartite matching, semi-clusters."""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph.model import PropertyGraph
from ..model.algebra import MIN
from ..model.program import VertexProgram
from ..model.superstep import RunResult, run
from ..runtime.scratch import drop, read_all, save


@dataclass(frozen=True)
class Stage:
    """A program and the direction its messages go."""

    program: VertexProgram
    direction: str = "out"
    max_steps: int | None = None


def run_stages(g: PropertyGraph, stages: list[Stage]) -> list[RunResult]:
    """Run stages one after the other over the graph or its transposed copy; each is seeded on its own."""
    both = {"out": g.edges, "in": g.transpose().edges}
    return [run(both[s.direction], g.vertices, s.program, s.max_steps) for s in stages]


def strong_components(g: PropertyGraph) -> DataFrame:
    """(id, scc): the smallest id of each strong component; no rows for no vertices.

    A round peels vertices without in- or out-edges, then spreads the smallest ancestor id forward as a
    colour and, from vertices that kept their own id, confirms backward within the colour. What rounds find is read as one
    table, so the plan doesn't grow with them.
    """
    left, edges, found = save(g.vertices.select("id"), "left"), save(g.edges.select("src", "dst").where("src <> dst").distinct(), "edges"), []
    while True:
        lone = left.join(edges.select(F.col("src").alias("id")), "id", "left_anti").unionByName(left.join(edges.select(F.col("dst").alias("id")), "id", "left_anti")).distinct()
        done = lone.select("id", F.col("id").alias("scc"))
        lone = save(done, "lone")
        if lone.limit(1).count():
            found.append(lone)
        else:
            if left.limit(1).count() == 0:
                break
            forward = VertexProgram("colour", F.col("id"), lambda r: r, lambda out, e: out, MIN, lambda old, acc: F.least(old, acc), rearm=lambda old, new: new < old, retire=True)
            colours = run(edges, left, forward).frame.withColumnRenamed("result", "colour")
            same = edges.join(colours.withColumnRenamed("id", "src"), "src").join(colours.select(F.col("id").alias("dst"), F.col("colour").alias("c2")), "dst").where("colour = c2")
            backward = save(same.select(F.col("dst").alias("src"), F.col("src").alias("dst")), "backward")
            confirm = VertexProgram(
                "confirm", F.col("colour") == F.col("id"), lambda r: r, lambda out, e: F.lit(0), MIN, lambda old, acc: F.lit(True), active=F.col("colour") == F.col("id"), rearm=lambda old, new: ~old, retire=True, attributes=("colour",)
            )
            reached = run(backward, colours, confirm).state.where("result").select("id", F.col("colour").alias("scc"))
            lone = save(reached, "strong")
            found.append(lone)
        gone = lone.select("id")
        next_left = save(left.join(gone, "id", "left_anti"), "left")
        kept = edges.join(gone.withColumnRenamed("id", "src"), "src", "left_anti").join(gone.withColumnRenamed("id", "dst"), "dst", "left_anti")
        next_edges = save(kept.select("src", "dst"), "edges")
        drop(g.spark, left, edges)
        left, edges = next_left, next_edges
    if not found:
        return left.select("id", F.col("id").alias("scc"))
    return read_all(found)


def betweenness(g: PropertyGraph, sources: DataFrame) -> DataFrame:
    """(id, score): sum over the sources of the shares of shortest paths through a vertex (directed, unweighted).

    Forward, each level counts paths from every source at once; backward, dependencies fold level by level.
    """
    edges = g.edges.select("src", "dst").where("src <> dst").distinct().persist()
    first = save(sources.select(F.col("id").alias("s"), "id", F.lit(1.0).alias("sigma")), "level")
    levels, seen = [first], first.select("s", "id")
    while True:
        step = levels[-1].join(edges, F.col("id") == F.col("src")).groupBy("s", F.col("dst").alias("id")).agg(F.sum("sigma").alias("sigma"))
        fresh = save(step.join(seen, ["s", "id"], "left_anti"), "level")
        if fresh.limit(1).count() == 0:
            break
        levels.append(fresh)
        seen = seen.unionByName(fresh.select("s", "id"))
    deeper, parts = levels[-1].withColumn("delta", F.lit(0.0)), []
    for level in reversed(levels[:-1]):
        parts.append(deeper.where("s <> id").select("id", "delta"))
        below = edges.join(deeper.select("s", F.col("id").alias("dst"), F.col("sigma").alias("sw"), F.col("delta").alias("dw")), "dst")
        share = below.join(level, (F.col("src") == level["id"]) & (below["s"] == level["s"])).select(level["s"], level["id"], (F.col("sigma") / F.col("sw") * (1 + F.col("dw"))).alias("x"))
        folded = share.groupBy("s", "id").agg(F.sum("x").alias("delta"))
        deeper = save(level.join(folded, ["s", "id"], "left").fillna(0.0, ["delta"]), "delta")
    parts.append(deeper.where("s <> id").select("id", "delta"))
    total = parts[0]
    for p in parts[1:]:
        total = total.unionByName(p)
    sums = total.groupBy("id").agg(F.sum("delta").alias("score"))
    return g.vertices.select("id").join(sums, "id", "left").fillna(0.0, ["score"])


def _priority(seed: int, step: int, *columns: str):
    return F.xxhash64(F.lit(seed), F.lit(step), *columns)


def bipartite_matching(g: PropertyGraph, seed: int = 7, max_rounds: int = 1000) -> DataFrame:
    """(src, dst): a maximal matching of a graph whose edges go from one side to the other.

    A round is a handshake: free left vertices ask all free neighbours, each right vertex grants the
    request with the lowest scrambled priority, each left vertex accepts its lowest grant.
    """
    open_edges, matched = save(g.edges.select("src", "dst").distinct(), "open"), []
    for r in range(max_rounds):
        if open_edges.limit(1).count() == 0:
            break
        ranked = open_edges.withColumn("p", _priority(seed, r, "src", "dst"))
        grants = ranked.groupBy("dst").agg(F.min(F.struct("p", "src")).alias("g")).select(F.col("g.src").alias("src"), "dst", F.col("g.p").alias("p"))
        accepted = save(grants.groupBy("src").agg(F.min(F.struct("p", "dst")).alias("g")).select("src", F.col("g.dst").alias("dst")), "matched")
        matched.append(accepted)
        rest = save(open_edges.join(accepted.select("src"), "src", "left_anti").join(accepted.select("dst"), "dst", "left_anti"), "open")
        drop(g.spark, open_edges)
        open_edges = rest
    out = g.edges.select("src", "dst").limit(0)
    for m in matched:
        out = out.unionByName(m.select("src", "dst"))
    return out


def semi_clusters(g: PropertyGraph, max_size: int = 4, top_n: int = 3, boundary: float = 0.5, steps: int = 3) -> DataFrame:
    """(id, cluster, score): each vertex's best semi-clusters of an undirected weighted graph.

    score = (inner weight - boundary * crossing weight) / (n (n - 1) / 2). A vertex offers its clusters to
    its neighbours, which may join them; the best ``top_n`` that hold the vertex stay, so a payload is at most top_n * max_size ids.
    """
    w = F.col("w").cast("double") if "w" in g.edges.columns else F.lit(1.0)
    one_way = g.edges.select("src", "dst", w.alias("w")).where("src <> dst")
    both = one_way.unionByName(one_way.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")).groupBy("src", "dst").agg(F.sum("w").alias("w")).persist()
    around = both.groupBy(F.col("src").alias("id")).agg(F.map_from_entries(F.collect_list(F.struct("dst", "w"))).alias("near"), F.sum("w").alias("degree"))
    cluster = "array<struct<members:array<long>,inner:double,cross:double,score:double>>"
    state = save(around.select("id", "near", "degree", F.expr(f"cast(array(named_struct('members', array(id), 'inner', 0.0D, 'cross', degree, 'score', 1.0D)) AS {cluster})").alias("best")), "clusters")

    kind = pa.list_(pa.struct([("members", pa.list_(pa.int64())), ("inner", pa.float64()), ("cross", pa.float64()), ("score", pa.float64())]))

    def extend(batches):
        for f in batches:
            made = []
            for v, near, degree, best, offered in zip(*(f.column(c).to_pylist() for c in ("id", "near", "degree", "best", "offered"))):
                near, known = dict(near), {}
                for c in [*best, *(c for group in offered or () for c in group)]:
                    members = tuple(c["members"])
                    if v in members:
                        known[members] = (c["score"], c["inner"], c["cross"])
                    elif len(members) < max_size:
                        gain = sum(near.get(u, 0.0) for u in members)
                        inner, cross = c["inner"] + gain, c["cross"] - gain + degree - gain
                        n = len(members) + 1
                        known[tuple(sorted((*members, v)))] = ((inner - boundary * cross) / (n * (n - 1) / 2), inner, cross)
                chosen = sorted(known.items(), key=lambda kv: (-kv[1][0], kv[0]))[:top_n]
                made.append([{"members": list(m), "inner": i, "cross": x, "score": s} for m, (s, i, x) in chosen])
            yield pa.RecordBatch.from_arrays([f.column("id"), pa.array(made, kind)], ["id", "best"])

    for _ in range(steps):
        sent = both.join(state.select(F.col("id").alias("src"), "best"), "src").groupBy(F.col("dst").alias("id")).agg(F.collect_list("best").alias("offered"))
        grown = state.join(sent, "id", "left").mapInArrow(extend, f"id long, best {cluster}")
        after = save(state.select("id", "near", "degree").join(grown, "id"), "clusters")
        drop(g.spark, state)
        state = after
    both.unpersist()
    return state.select("id", F.explode("best").alias("c")).select("id", F.col("c.members").alias("cluster"), F.col("c.score").alias("score"))
