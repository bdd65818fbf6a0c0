"""Greedy streaming placement of edges, directional or not.

The next edge (u, v) goes to the part with the highest score: 1 if u is present there as a source, 1 if v
is present as a target, and a load term below 1 that favours parts with fewer edges; ties go to the lowest
part. The undirected variant, which vertex-cut comparators use, counts any presence of either end.
``capacity_guard`` = e closes parts that hold more than (1 + e) times their share.

``serial`` has one loader that sees everything; ``oblivious`` loaders know only their own edges;
``coordinated`` loaders place ``sync_every`` edges each and then merge what they know. A loader reads its edges
as a stream of Arrow batches and holds only its tables, whole-number bit sets of parts per vertex, so the number
of parts has no bound. Presence that coordinated loaders share is an array of 63-bit words per vertex.

Only parts where an end is present and the least loaded open part can have the highest score, so a placement
costs the number of the former, not k.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime.scratch import drop, new_path, save
from .stream_order import loader_of, order_edges, sort_keys

DELTA = 1.0
#: Parts in a word of shared presence.
WORD = 63


@dataclass
class LoaderTables:
    """What a loader knows: parts that have a vertex as source or target, and edges per part.

    The bit sets are lists where vertices are numbers from 0, which is faster; :meth:`make_room` lengthens them.
    """

    k: int
    directed: bool = True
    delta: float = DELTA
    guard: float | None = None
    out_bits: dict[int, int] | list[int] = field(default_factory=lambda: defaultdict(int))
    in_bits: dict[int, int] | list[int] = field(default_factory=lambda: defaultdict(int))
    loads: np.ndarray | None = None
    members: dict[int, tuple[int, ...]] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.loads = np.zeros(self.k, dtype=np.int64) if self.loads is None else self.loads
        if not self.directed:
            self.in_bits = self.out_bits

    def make_room(self, n: int) -> None:
        """Lengthen lists to ``n`` vertices."""
        for bits in (self.out_bits, self.in_bits):
            bits += [0] * (n - len(bits))

    def place(self, sources: np.ndarray, targets: np.ndarray) -> np.ndarray:
        """Parts of a run of edges, updating the tables after each."""
        if self.guard is None and self.k <= WORD and self.delta == DELTA:
            return self.place_few(sources, targets)
        k, loads, out_bits, in_bits = self.k, self.loads.tolist(), self.out_bits, self.in_bits
        low, high, total = min(loads), max(loads), sum(loads)
        least = [(n, i) for i, n in enumerate(loads)]  # (load, part), entries of old loads are passed over
        heapify(least)
        parts = np.empty(len(sources), dtype=np.int32)
        for n, (u, v) in enumerate(zip(sources.tolist(), targets.tolist())):
            bu, bv = out_bits[u], in_bits[v]
            limit = None if self.guard is None else max((1 + self.guard) * (total + 1) / k, low + 1)
            scale = self.delta + high - low
            while least[0][0] != loads[least[0][1]]:
                heappop(least)
            best, chosen = (high - low) / scale, least[0][1]  # the least loaded part is always open
            best += (bu >> chosen & 1) + (bv >> chosen & 1)
            held = bu | bv
            while held:
                bit = held & -held
                i, held = bit.bit_length() - 1, held ^ bit
                if limit is not None and loads[i] + 1 > limit:
                    continue
                score = (bu >> i & 1) + (bv >> i & 1) + (high - loads[i]) / scale
                if score > best or (score == best and i < chosen):
                    best, chosen = score, i
            parts[n] = chosen
            out_bits[u] = bu | 1 << chosen
            in_bits[v] |= 1 << chosen
            loads[chosen] += 1
            heappush(least, (loads[chosen], chosen))
            total += 1
            high = max(high, loads[chosen])
            if loads[chosen] - 1 == low:
                while least[0][0] != loads[least[0][1]]:
                    heappop(least)
                low = least[0][0]
        self.loads = np.array(loads, dtype=np.int64)
        return parts

    def place_few(self, sources: np.ndarray, targets: np.ndarray) -> np.ndarray:
        """:meth:`place` for few parts that all stay open.

        The load term is below 1, so the best part is the least loaded of those with both ends, else of those with one,
        else of all; ``min`` takes the lowest of equals.
        """
        loads, out_bits, in_bits, members = self.loads.tolist(), self.out_bits, self.in_bits, self.members
        load = loads.__getitem__
        parts = []
        for u, v in zip(sources.tolist(), targets.tolist()):
            bu, bv = out_bits[u], in_bits[v]
            both = bu & bv
            held = both or bu | bv
            if not held:
                chosen = loads.index(min(loads))
            elif held & held - 1:
                among = members.get(held)
                if among is None:
                    among = tuple(i for i in range(self.k) if held >> i & 1)
                    if len(members) < 1 << 16:
                        members[held] = among
                if len(among) == 2:
                    chosen, other = among
                    if loads[other] < loads[chosen]:
                        chosen = other
                else:
                    chosen = min(among, key=load)
            else:
                chosen = held.bit_length() - 1
            if not both:
                out_bits[u] |= 1 << chosen
                in_bits[v] |= 1 << chosen
            loads[chosen] += 1
            parts.append(chosen)
        self.loads = np.array(loads, dtype=np.int64)
        return np.array(parts, dtype=np.int32)


#: Rows of a placement.
PLACED = "edge_seq long, src long, dst long, loader int, pid int"


def with_parts(batch: pa.RecordBatch, parts: np.ndarray) -> pa.RecordBatch:
    names = ["edge_seq", "src", "dst", "loader"]
    return pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(parts, pa.int32())], [*names, "pid"])


def runs(batches: Iterator[pa.RecordBatch], key: str = "loader") -> Iterator[tuple[int, pa.RecordBatch]]:
    """(loader, its next edges) of batches in which a loader's edges lie side by side."""
    for batch in batches:
        loader = np.asarray(batch.column(key))
        cuts = np.flatnonzero(np.diff(loader, prepend=-1)).tolist()
        for a, b in zip(cuts, [*cuts[1:], len(loader)]):
            yield int(loader[a]), batch.slice(a, b - a)


def by_loader(rows: DataFrame, loaders: int) -> DataFrame:
    """Each loader's edges in one task, in their order; the sort can spill, and nothing else holds them."""
    return rows.repartition(loaders, "loader").sortWithinPartitions("loader", "edge_seq")


def _per_loader(ordered: DataFrame, loaders: int, k: int, directed: bool, delta: float, guard: float | None) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, tables = None, None
        for loader, batch in runs(batches):
            if loader != now:
                now, tables = loader, LoaderTables(k, directed, delta, guard)
            yield with_parts(batch, tables.place(np.asarray(batch.column("src")), np.asarray(batch.column("dst"))))

    return by_loader(ordered, loaders).mapInArrow(run, PLACED)


def greedy_place(
    edges: DataFrame,
    k: int,
    direction: str = "directed",
    ingress: str = "oblivious",
    loaders: int = 8,
    order: str = "mixed",
    delta: float = DELTA,
    capacity_guard: float | None = None,
    sync_every: int = 1024,
    two_pass: bool = False,
) -> DataFrame:
    """(edge_seq, src, dst, loader, pid) for every edge.

    ``two_pass`` counts degrees first and streams edges of high-degree vertices first.
    """
    directed = direction == "directed"
    order = "degree" if two_pass else order
    if ingress == "serial":
        return _per_loader(order_edges(edges, order, 1), 1, k, directed, delta, capacity_guard)
    ordered = order_edges(edges, order, loaders)
    if ingress == "oblivious":
        return _per_loader(ordered, loaders, k, directed, delta, capacity_guard)
    if ingress == "coordinated":
        return coordinated(ordered, k, directed, delta, capacity_guard, sync_every, loaders)
    raise ValueError(f"unknown ingress {ingress}")


#: Rows of what placements put where. A vertex's edges in a part may be spread over several rows.
PRESENT = "graph int, way int, id long, pid int, out long, into long"
#: Edges in order, many to a row, for a placing task.
PACKED = "task int, at long, edges binary"
#: Stretches of a graph's order that are sorted apart (a power of two up to 2^60).
BANDS = 64
#: Edges in a packed row and of a step of a loader, and most counts that wait or are held.
PACK, STEP, COUNTED = 1 << 11, 1 << 16, 1 << 22


class Numbers:
    """Vertices of a loader, numbered from 0 as they come; ``known`` is sorted and ``number`` lies beside it."""

    def __init__(self) -> None:
        self.known, self.number = np.empty(0, np.int64), np.empty(0, np.int64)

    def of(self, vertices: np.ndarray) -> np.ndarray:
        now, nth = np.unique(vertices, return_inverse=True)
        at = np.searchsorted(self.known, now)
        fresh = np.append(self.known, 0)[at] != now
        fresh |= at == len(self.known)
        if fresh.any():
            new = len(self.known) + np.arange(np.count_nonzero(fresh))
            self.known, self.number = np.insert(self.known, at[fresh], now[fresh]), np.insert(self.number, at[fresh], new)
            at = np.searchsorted(self.known, now)
        return self.number[at][nth]

    def vertices(self) -> np.ndarray:
        """The vertex of every number."""
        found = np.empty_like(self.known)
        found[self.number] = self.known
        return found


class Counts:
    """Edges out of and into vertices per part. They are given up when there are ``COUNTED`` of them, so memory stays bounded."""

    def __init__(self, graph: int, way: int, k: int):
        self.graph, self.way, self.k, self.numbers, self.held, self.waiting = graph, way, k, Numbers(), [], 0
        self.keys, self.edges = np.empty(0, np.int64), np.empty(0, np.int64)

    def add(self, sources: np.ndarray, targets: np.ndarray, parts: np.ndarray) -> None:
        self.held += [2 * (sources * self.k + parts), 2 * (targets * self.k + parts) + 1]
        self.waiting += 2 * len(parts)

    def merge(self) -> None:
        """Add what waits to the counts, which are sorted."""
        if self.waiting:
            keys, n = np.unique(np.concatenate(self.held), return_counts=True)
            self.held, self.waiting = [], 0
            at = np.searchsorted(self.keys, keys)
            old = np.append(self.keys, -1)[at] == keys
            self.edges[at[old]] += n[old]
            self.keys, self.edges = np.insert(self.keys, at[~old], keys[~old]), np.insert(self.edges, at[~old], n[~old])

    def rows(self) -> Iterator[pa.RecordBatch]:
        self.merge()
        keys, n = self.keys, self.edges
        self.keys, self.edges = keys[:0], n[:0]
        number, pid = np.divmod(keys >> 1, self.k)
        into = np.where(keys & 1, n, 0)
        ids = self.numbers.vertices()[number]
        fixed = [np.full(len(keys), x, np.int32) for x in (self.graph, self.way)]
        columns = [*fixed, ids, pid.astype(np.int32), n - into, into]
        for a in range(0, len(keys), STEP):
            yield pa.RecordBatch.from_arrays([pa.array(c[a : a + STEP]) for c in columns], ["graph", "way", "id", "pid", "out", "into"])


def place_each_way(edges: DataFrame, graphs: int, ways: list[tuple[int, str, str]], loaders: int = 8, order: str = "digest") -> DataFrame:
    """(graph, way, id, pid, out, into): edges of vertices per part when each of ``ways`` (k, direction, ingress) places every edge (graph, src, dst).

    Placements are those of :func:`greedy_place`. They don't depend on each other, so every loader of every graph and
    way has a task of its own. A graph's order is sorted once, in stretches, and handed to these tasks in packed rows;
    they return no edges but counts, to be summed by (graph, way, id, pid). ``ways`` are serial or oblivious.
    """
    known, keys = sort_keys(edges.select("graph", "src", "dst"), order)
    band = F.lit(0)
    if order == "digest":  # a whole number sorts faster than text, and decides nearly always
        known = known.withColumn("_key", F.conv(F.substring(keys[0], 1, 15), 16, 10).cast("long"))
        keys, band = ["_key", *keys], F.shiftright("_key", 61 - BANDS.bit_length()).cast("int")
    dealt = known.withColumns({"loader": loader_of(loaders), "band": F.col("graph") * BANDS + band})
    ordered = dealt.repartitionById(graphs * BANDS, "band").sortWithinPartitions("band", *keys).select("band", "loader", "src", "dst")

    many = [loaders if ingress == "oblivious" else 1 for _, _, ingress in ways]
    longest_first = sorted(range(len(ways)), key=lambda w: many[w])
    tasks = [(w, i if many[w] > 1 else None) for w in longest_first for i in range(many[w])]  # (way, loader), None: all edges

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: dict[int, int] = {}  # next row of a band
        for band, batch in runs(batches, "band"):
            loader, ends = np.asarray(batch.column("loader")), np.column_stack([np.asarray(batch.column(c)) for c in ("src", "dst")])
            of = {i: ends if i is None else ends[loader == i] for i in {i for _, i in tasks}}
            packs = {i: [x[a : a + PACK].tobytes() for a in range(0, len(x), PACK)] for i, x in of.items()}
            rows = [(n * graphs + band // BANDS, x) for n, (_, i) in enumerate(tasks) for x in packs[i]]
            start = at.get(band, 0)
            at[band] = start + len(rows)
            nth = np.arange(start, at[band]) + (band % BANDS << 40)
            yield pa.RecordBatch.from_arrays([pa.array([t for t, _ in rows], pa.int32()), pa.array(nth), pa.array([x for _, x in rows], pa.binary())], ["task", "at", "edges"])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, counts = None, None
        for task, batch in runs(batches, "task"):
            if task != now:
                if counts:
                    yield from counts.rows()
                nth, graph = divmod(task, graphs)
                way = tasks[nth][0]
                now, counts, tables = task, Counts(graph, way, ways[way][0]), LoaderTables(ways[way][0], ways[way][1] == "directed", out_bits=[], in_bits=[])
            packed = batch.column("edges")
            for a in range(0, len(packed), STEP // PACK):
                ends = np.frombuffer(b"".join(packed[a : a + STEP // PACK].to_pylist()), np.int64).reshape(-1, 2)
                sources, targets = counts.numbers.of(ends.ravel()).reshape(-1, 2).T
                tables.make_room(len(counts.numbers.known))
                counts.add(sources, targets, tables.place(sources, targets))
                if counts.waiting >= COUNTED:
                    counts.merge()
                    if len(counts.keys) >= COUNTED:
                        yield from counts.rows()
        if counts:
            yield from counts.rows()

    return ordered.mapInArrow(pack, PACKED).repartitionById(len(tasks) * graphs, "task").sortWithinPartitions("task", "at").mapInArrow(place, PRESENT)


#: Most rounds of a coordinated placement.
MOST_ROUNDS = 256


def _round_placer(k: int, directed: bool, delta: float, guard: float | None, start: np.ndarray):
    """Function that places loaders' edges of a round from merged loads and the presence (bu, bv) joined to them."""

    def whole(words: list[int] | None) -> int:
        return sum(w << WORD * i for i, w in enumerate(words or ()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, tables = None, None
        for loader, batch in runs(batches):
            if loader != now:
                now, tables = loader, LoaderTables(k, directed, delta, guard, loads=start.copy())
            source, target = batch.column("src").to_pylist(), batch.column("dst").to_pylist()
            for u, v, bu, bv in zip(source, target, batch.column("bu").to_pylist(), batch.column("bv").to_pylist()):
                if bu:
                    tables.out_bits[u] = tables.out_bits.get(u, 0) | whole(bu)
                if bv:
                    tables.in_bits[v] = tables.in_bits.get(v, 0) | whole(bv)
            yield with_parts(batch, tables.place(np.array(source, dtype=np.int64), np.array(target, dtype=np.int64)))

    return run


class SharedTables:
    """Presence and loads that loaders share, merged after every round.

    Presence is sparse rows (id, out_words, in_words) and a round joins only the ids it names; the loads, k
    numbers, are on the driver. A round's edges are written once and never read by later rounds.
    """

    def __init__(self, spark: SparkSession, k: int, directed: bool = True, delta: float = DELTA, guard: float | None = None, loaders: int = 8):
        self.spark, self.k, self.directed, self.delta, self.guard, self.loaders = spark, k, directed, delta, guard, loaders
        self.presence: DataFrame | None = None
        self.loads, self.out, self.rounds = np.zeros(k, dtype=np.int64), new_path(spark, "placed"), []

    def place(self, now: DataFrame) -> None:
        """Place one round's rows (edge_seq, src, dst, loader)."""
        if self.presence is None:
            known = now.withColumns({c: F.lit(None).cast("array<bigint>") for c in ("bu", "bv")})
        else:
            known = now.join(self.presence.select(F.col("id").alias("src"), F.col("out_words").alias("bu")), "src", "left")
            known = known.join(self.presence.select(F.col("id").alias("dst"), F.col("in_words" if self.directed else "out_words").alias("bv")), "dst", "left")
        done = by_loader(known, self.loaders).mapInArrow(_round_placer(self.k, self.directed, self.delta, self.guard, self.loads.copy()), PLACED)
        path = f"{self.out}/r={len(self.rounds)}"
        done.write.parquet(path)
        self.rounds.append(path)
        placed = self.spark.read.schema(PLACED).parquet(path)
        for row in placed.groupBy("pid").count().collect():  # k rows
            self.loads[row["pid"]] += row["count"]
        self._merge(placed)

    def _merge(self, placed: DataFrame) -> None:
        n_words = -(-self.k // WORD)
        blank = [F.lit(0).cast("long")] * n_words
        bits = [F.when(F.expr(f"pid div {WORD}") == i, F.expr(f"shiftleft(1L, pid % {WORD})")).otherwise(blank[0]) for i in range(n_words)]
        outs, ins = ([f"{side}{i}" for i in range(n_words)] for side in "oi")

        def of(end: str, out: list, into: list) -> DataFrame:
            return placed.select(F.col(end).alias("id"), *(c.alias(n) for c, n in zip([*out, *into], [*outs, *ins])))

        seen = of("src", bits, blank).unionByName(of("dst", blank if self.directed else bits, bits))
        if self.presence is not None:
            held = (F.col(words)[i].alias(n) for words, names in (("out_words", outs), ("in_words", ins)) for i, n in enumerate(names))
            seen = seen.unionByName(self.presence.select("id", *held))
        merged = seen.groupBy("id").agg(*(F.bit_or(c).alias(c) for c in (*outs, *ins)))
        before, self.presence = self.presence, save(merged.select("id", F.array(*outs).alias("out_words"), F.array(*ins).alias("in_words")), "presence")
        if before is not None:
            drop(self.spark, before)

    def frame(self) -> DataFrame:
        """All rounds' rows (edge_seq, src, dst, loader, pid)."""
        return self.spark.read.schema(PLACED).parquet(*self.rounds)


def coordinated(ordered: DataFrame, k: int, directed: bool, delta: float, guard: float | None, sync_every: int, loaders: int) -> DataFrame:
    """Rounds of ``sync_every`` edges per loader; presence and loads merge between rounds.

    The edges are written once, a folder per round, and a round reads its own only. Rounds grow with the edges,
    so ``sync_every`` is raised where there would be more than ``MOST_ROUNDS``.
    """
    spark = ordered.sparkSession
    listed = save(ordered, "ordered")
    longest = (listed.agg(F.max("edge_seq")).first()[0] or 0) + 1
    sync_every = max(sync_every, -(-longest // MOST_ROUNDS))
    by_round, tables = new_path(spark, "rounds"), SharedTables(spark, k, directed, delta, guard, loaders)
    listed.withColumn("round", F.expr(f"edge_seq div {sync_every}")).repartition("round").write.partitionBy("round").parquet(by_round)
    for r in range(-(-longest // sync_every)):
        path = f"{by_round}/round={r}"
        tables.place(spark.read.schema(ordered.schema).parquet(path) if longest > 1 or _exists(spark, path) else ordered.limit(0))
    drop(spark, listed)
    return tables.frame()


def _exists(spark, path: str) -> bool:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where)


def brute_place(edges: list[tuple[int, int]], k: int, directed: bool = True, delta: float = DELTA) -> list[int]:
    """Reference for tests: the rule as stated, over plain sets."""
    outs, ins, loads, parts = [set() for _ in range(k)], [set() for _ in range(k)], [0] * k, []
    for u, v in edges:
        high, low = max(loads), min(loads)
        scores = []
        for i in range(k):
            f = u in outs[i] if directed else (u in outs[i] or u in ins[i])
            g = v in ins[i] if directed else (v in outs[i] or v in ins[i])
            scores.append(f + g + (high - loads[i]) / (delta + high - low))
        i = scores.index(max(scores))
        parts.append(i), outs[i].add(u), ins[i].add(v)
        loads[i] += 1
    return parts
