"""N-gram Jaccard join on a count-vector R-tree.

A document is the set of its distinct k-word shingles; two documents link when
100 * |A n B| >= percent * |A u B|. Shingles are hashed into groups, and a document is the point of its
group counts. No pair of points can share more shingles than the sum of their coordinate minima, and a
linked pair differs by at most D = (100 - percent) * (|A| + |B|) / (100 + percent) shingles, hence by at
most D in the sum of coordinate differences.

Equal sets are one class, represented by their smallest id; only representatives go on. Every link comes from
a search of an R-tree over count points and from an exact check of what the search returns:

1. *Tiles* split the points before the search. A fine point of M blocks of coordinates, M > D: at most D
   blocks can differ, so every linked pair has a block whose counts are equal - one tile holds both. M depends
   on the size, so sizes are cut into scales; a document goes into its own scale and, where a larger one may
   link to it, the next. Blocks with one shingle or none make tiles only for documents with too few others
   (see ``tile_keys``). Of tiles with the same members one stays. Tiles known to be hot from partial counts
   are dealt into chunks and never pass through a sort by tile.
2. *First hits.* Each tile (or chunk of one) is an R-tree packed by id. A search descends, smallest ids first,
   only where the sum of minima with a box's upper corner reaches the need, and ends at its first hit: one
   pair per member, and about one leaf per member in a group of near copies. Verified pairs give components.
3. *All hits.* Tiles of more than two members, some hit and several components get a tree packed by component, and
   a search returns all hits of other components. A tile whose hits are few beside its members gives them
   as pairs; otherwise the members that hits connect become one group, so that a tile never gives more
   rows than a multiple of its members. Groups are verified by one task each (or each pair of chunks) from an
   inverted index of the members' shingles, joining components as links are found and ending at one.

A pair within one component needs no check for the components to be exact. A family of m texts that are near
each other but not linked costs up to m * m bounds and overlaps inside tasks, and about m rows.

Cases: words are runs of characters outside x20 and x09-x0D, with A-Z lower-cased; a text of 1 to k-1
words is one shingle; null, empty and wordless texts have no shingles and link with nothing; rows with
one id are one vertex, linked by the sets of each; a null id has a null component and links with
nothing; empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..algorithms.contract import contract_components
from ..runtime.scratch import drop, save
from .hashing import mixed, pieces, shingles, words

LEAST_GROUPS, MOST_GROUPS, CELLS, FANOUT = 64, 2048, 16, 16
#: Blocks of at most so many shingles are light.
LIGHT = 1
#: Most members of a chunk of a tile, most ids or pairs that are broadcast, and most counts of points compared at once.
UNIT, BROADCAST_IDS, CELLS_AT_ONCE = 4096, 500_000, 1_000_000
#: Rows of one tile in one task from which on they count for finding hot tiles, and keys counted at once.
LOCAL, KEYS_AT_ONCE = 16, 8_000_000
#: Most pairs per member that a tile gives before it gives groups, and shingles of a chunk of a group.
PAIRS_A_MEMBER, GROUP_SHINGLES = 2, 2_000_000


def scales(percent: int, most: int = 2**40) -> np.ndarray:
    """Upper size of every scale: 1, 2, ... and then growing by half."""
    tops = [1]
    while tops[-1] < most:
        tops.append(max(tops[-1] + 1, tops[-1] * 3 // 2))
    return np.array(tops, dtype=np.int64)


def differing(percent: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Most shingles by which linked sets of these sizes can differ."""
    return (100 - percent) * (a + b) // (100 + percent)


def needed(percent: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least overlap of linked sets of these sizes."""
    return -(-percent * (a + b) // (100 + percent))


def dimensions(sizes: np.ndarray) -> np.ndarray:
    """Groups of a point: a power of two, one to two shingles a group.

    Fewer groups would let the minima of unlike long documents add up to the need. A point folds to half
    as many groups by adding its halves, so points of different sizes compare at the smaller of the two.
    """
    wanted = 1 << np.ceil(np.log2(np.maximum(sizes, 2) / 2)).astype(np.int64)
    return np.clip(wanted, LEAST_GROUPS, MOST_GROUPS)


def slack(most: np.ndarray, top: np.ndarray) -> np.ndarray:
    """Blocks beyond D + 1: about as many as a row of the scale has light ones, so that few rows need those.

    Light blocks make poor tiles: one frequent shingle alone would bring unlike documents together. Any
    slack is right; this one is cheap.
    """
    blocks = most + 3
    load = 0.8 * top / blocks
    return 2 + np.ceil(1.3 * np.exp(-load) * (1 + load) * blocks).astype(np.int64)


def tile_keys(hashes: np.ndarray, sizes: np.ndarray, percent: int, tops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) of all tiles of rows whose sorted shingle hashes are concatenated.

    With M = D + 1 + slack blocks at least slack + 1 blocks of a linked pair are equal. Heavy blocks are
    always tiles. They are enough if either row has at most slack light ones, since one of the equal blocks is
    heavy then. Rows with more add their blocks of one shingle, and rows with more than slack empty
    blocks add these too: a pair that shares only such blocks has rows that both add them.

    Keys have 48 bits, the low ones being 0, which makes them a sixth shorter when shuffled. Tiles that fall together
    by chance cost a comparison and nothing else.
    """
    first = np.concatenate([[0], np.cumsum(sizes)])
    own = np.searchsorted(tops, sizes)
    out_row, out_key = [], []
    for shift in range(2 + int(np.log(100 / percent) / np.log(1.5))):
        scale = own + shift
        top = tops[scale]
        most = differing(percent, top, top)
        reach = (most > 0) & (sizes > 0)
        if shift:
            reach &= 100 * sizes >= percent * (tops[scale - 1] + 1)
        rows = np.flatnonzero(reach)
        if not len(rows):
            continue
        spare = slack(most[rows], top[rows])
        blocks = most[rows] + 1 + spare
        count = sizes[rows]
        of = np.repeat(np.arange(len(rows)), count)
        index = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(first[rows], count)
        h = hashes[index]
        # the upper half of a hash picks the block, so sorted hashes lie block by block; the rest picks the cell
        block = ((h >> np.uint64(32)) * blocks[of].astype(np.uint64)) >> np.uint64(32)
        salt = mixed(scale[rows].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))[of]
        base = (np.cumsum(blocks) - blocks)[of] + block.astype(np.int64)
        starts = np.flatnonzero(np.diff(base, prepend=-1))
        cells = mixed((h & np.uint64((1 << CELLS) - 1)) + salt + (block << np.uint64(20)))
        keys, owner = mixed(np.add.reduceat(cells, starts)), of[starts]
        heavy = np.diff(np.append(starts, len(h))) > LIGHT
        many = blocks - np.bincount(owner[heavy], minlength=len(rows)) > spare
        bare = blocks - np.bincount(owner, minlength=len(rows)) > spare
        used_tiles = heavy | many[owner]
        out_key.append(keys[used_tiles])
        out_row.append(rows[owner[used_tiles]])
        for i in np.flatnonzero(bare):
            used = np.unique(block[of == i])
            empty = np.setdiff1d(np.arange(blocks[i], dtype=np.uint64), used)
            out_key.append(mixed(mixed((empty << np.uint64(20)) + np.uint64(scale[rows[i]])) ^ np.uint64(0x5BD1E995)))
            out_row.append(np.full(len(empty), rows[i]))
    if not out_row:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.uint64)
    return np.concatenate(out_row), np.concatenate(out_key) & np.uint64(0xFFFFFFFFFFFF0000)


def sets_of(column: pa.Array, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first row, shingle hashes, their rows, set sizes) of pieces of a column of texts."""
    for first, data, bounds in pieces(column):
        hashes, rows, _, _ = words(data, bounds)
        yield first, *shingles(hashes, rows, len(bounds) - 1, k)


def point_table(docs: DataFrame, k: int, percent: int) -> DataFrame:
    """(id, n, s1, s2, point, often): set size, two sums that identify the set, coarse point.

    ``often`` is null but on an extra row of each task, where it has the tile keys that the task's rows hold at
    least ``LOCAL`` times.
    """
    id_type = docs.schema["id"].dataType.simpleString()
    tops = scales(percent)
    counts_type = pa.list_(pa.struct([("key", pa.int64()), ("seen", pa.int64())]))
    names = ["id", "n", "s1", "s2", "point", "often"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, id_kind = [], None

        def counted() -> pa.RecordBatch:
            key, count = np.unique(np.concatenate([np.zeros(0, dtype=np.uint64), *held]), return_counts=True)
            held.clear()
            often = [{"key": x, "seen": y} for x, y in zip(key[count >= LOCAL].view(np.int64).tolist(), count[count >= LOCAL].tolist())]
            zero = pa.array([0], pa.int64())
            return pa.RecordBatch.from_arrays([pa.nulls(1, id_kind), zero, zero, zero, pa.nulls(1, pa.binary()), pa.array([often], counts_type)], names)

        for batch in batches:
            id_kind = batch.column("id").type
            for first, h, rows, sizes in sets_of(batch.column("text"), k):
                n = len(sizes)
                at = np.concatenate([[0], np.cumsum(sizes)])
                sums = [np.concatenate([[np.uint64(0)], np.cumsum(mixed(h + c))]) for c in (np.uint64(1), np.uint64(2))]
                s1, s2 = ((x[at[1:]] - x[at[:-1]]).view(np.int64) for x in sums)
                groups = dimensions(sizes)
                base = np.concatenate([[0], np.cumsum(groups)])
                cell = base[rows] + (h & (groups[rows] - 1).astype(np.uint64)).astype(np.int64)
                counts = np.bincount(cell, minlength=base[-1])
                points = [packed(counts[x:y]) for x, y in zip(base[:-1].tolist(), base[1:].tolist())]
                held.append(tile_keys(h, sizes, percent, tops)[1])
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(first, n), pa.array(sizes.astype(np.int64)), pa.array(s1), pa.array(s2), pa.array(points, pa.binary()), pa.nulls(n, counts_type)], names)
                if sum(map(len, held)) >= KEYS_AT_ONCE:
                    yield counted()
        if held:
            yield counted()

    return docs.mapInArrow(run, f"id {id_type}, n long, s1 long, s2 long, point binary, often array<struct<key:long,seen:long>>")


def tile_table(docs: DataFrame, k: int, percent: int) -> DataFrame:
    """(node, keys): the tiles of every text."""
    id_type = docs.schema["id"].dataType.simpleString()
    tops = scales(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, h, _, sizes in sets_of(batch.column("text"), k):
                row, key = tile_keys(h, sizes, percent, tops)
                order = np.argsort(row, kind="stable")
                offsets = np.searchsorted(row[order], np.arange(len(sizes) + 1)).astype(np.int32)
                keys = pa.ListArray.from_arrays(pa.array(offsets), pa.array(key[order].view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(first, len(sizes)), keys], ["node", "keys"])

    return docs.mapInArrow(run, f"node {id_type}, keys array<long>")


def packed(counts: np.ndarray) -> bytes:
    """Counts as bytes, in half a byte each where they fit, else in one or four."""
    top = counts.max(initial=0)
    if top < 16:
        return (counts[::2] | counts[1::2] << 4).astype(np.uint8).tobytes()
    return counts.astype(np.uint8 if top < 256 else "<u4").tobytes()


def unpacked(points: list[bytes], sizes: np.ndarray, groups: int) -> np.ndarray:
    """Counts of points folded to ``groups``; a point's own number of groups follows from its set's size."""
    own = dimensions(sizes)
    length = np.fromiter(map(len, points), np.int64, len(points))
    plain = (length <= own) & (own == groups)
    out = np.zeros((len(points), groups), dtype=np.uint8 if plain.all() else np.uint32)
    for size, held in {*zip(own.tolist(), length.tolist())}:
        at = np.flatnonzero((own == size) & (length == held))
        raw = b"".join([points[i] for i in at.tolist()])
        counts = np.frombuffer(raw, "<u4" if held > size else np.uint8).reshape(len(at), -1)
        if held < size:
            halves = counts
            counts = np.empty((len(at), size), dtype=np.uint8)
            counts[:, ::2], counts[:, 1::2] = halves & 15, halves >> 4
        out[at] = counts.reshape(len(at), size // groups, groups).sum(axis=1) if size > groups else counts
    return out


def verified(pairs: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) of ids whose texts link; ``pairs`` is a written table.

    A text goes once to each of its pairs' first members and each of these once to its pairs. A first
    member with very many pairs is an ordinary skewed join, which may be split.
    """
    id_type = pairs.schema["a"].dataType.simpleString()
    small = pairs.count() <= BROADCAST_IDS
    spread = F.broadcast if small else lambda df: df
    seconds = docs.select(F.col("id").alias("b"), F.col("text").alias("tb")).join(spread(pairs), "b")
    firsts = docs.select(F.col("id").alias("a"), F.col("text").alias("ta")).join(spread(pairs.select("a").distinct()), "a", "left_semi")
    both = seconds.hint("merge").join(firsts, "a").select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_text, last_set = None, None
        for whole in batches:
            for start in range(0, whole.num_rows, 200):
                batch = whole.slice(start, 200)
                texts, keep = batch.column("ta"), np.zeros(batch.num_rows, dtype=bool)
                for first, h, _, sizes in sets_of(batch.column("tb"), k):
                    at = np.concatenate([[0], np.cumsum(sizes)])
                    for i, n in enumerate(sizes.tolist()):
                        if (text := texts[first + i].as_py()) != last_text:
                            last_text, last_set = text, next(sets_of(pa.array([text], pa.large_string()), k))[1]
                        mine = h[at[i] : at[i + 1]]
                        shared = len(np.intersect1d(mine, last_set, assume_unique=True))
                        keep[first + i] = shared > 0 and 100 * shared >= percent * (n + len(last_set) - shared)
                yield batch.select(["a", "b"]).filter(pa.array(keep))

    return both.mapInArrow(run, f"a {id_type}, b {id_type}").distinct()


class CountTree:
    """Packed R-tree over count points: every node has its boxes' upper corner, least size and components."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray, components: np.ndarray, order: np.ndarray):
        self.order = order
        self.points, self.sizes, self.components = points, sizes, components
        self.levels = [(points[order], sizes[order], components[order], components[order])]
        while len(self.levels[-1][0]) > 1:
            high, size, low_c, high_c = self.levels[-1]
            at = np.arange(0, len(high), FANOUT)
            self.levels.append((np.maximum.reduceat(high, at), np.minimum.reduceat(size, at), np.minimum.reduceat(low_c, at), np.maximum.reduceat(high_c, at)))

    def _may(self, depth: int, node: int, probes: np.ndarray, percent: int) -> np.ndarray:
        """The probes that the bounds let link with some point of other components below a node."""
        high, least, low_c, high_c = (x[node] for x in self.levels[depth])
        if low_c == high_c:
            probes = probes[self.components[probes] != low_c]
        step, kept = max(1, CELLS_AT_ONCE // len(high)), [probes[:0]]
        for a in range(0, len(probes), step):
            some = probes[a : a + step]
            kept.append(some[np.minimum(self.points[some], high).sum(axis=1, dtype=np.int64) >= needed(percent, least, self.sizes[some])])
        return np.concatenate(kept)

    def search(self, percent: int, first_only: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(members, one hit of theirs) arrays; hits come before their member, in its order, and differ in component.

        All members are searched for together: each node is visited with the members that may have a hit below
        it. With ``first_only`` a member's search ends at its first hit.
        """
        place = np.empty(len(self.order), dtype=np.int64)
        place[self.order] = np.arange(len(self.order))
        found = np.zeros(len(self.order), dtype=bool)
        stack = [(len(self.levels) - 1, 0, self.order)]
        while stack:
            depth, node, probes = stack.pop()
            if first_only:
                probes = probes[~found[probes]]
            probes = self._may(depth, node, probes[place[probes] > node * FANOUT**depth], percent)
            if not len(probes):
                continue
            if depth:
                below = range(node * FANOUT, min((node + 1) * FANOUT, len(self.levels[depth - 1][0])))
                stack += [(depth - 1, child, probes) for child in reversed(below)]
                continue
            found[probes] = True
            yield probes, np.full(len(probes), self.order[node])


def tile_hits(points: list[bytes], sizes: np.ndarray, components: np.ndarray, starts: np.ndarray, percent: int, first_only: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, hits) of different components that the bound lets link, within tiles that begin at ``starts``.

    A tile of at most ``FANOUT`` members is a single leaf; leaves of one size are searched together. A larger one
    gets a tree, packed by row for first hits, else by component and size. Points of a tile compare at its
    smallest number of groups; what is held of a tile is at most 2 * ``UNIT`` points of ``MOST_GROUPS`` counts.
    """
    counts = np.diff(np.append(starts, len(sizes)))
    groups = np.minimum.reduceat(dimensions(sizes), starts)

    def leaves(of: np.ndarray, m: int, g: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        rows = (of[:, None] + np.arange(m)).ravel()
        held = unpacked([points[r] for r in rows.tolist()], sizes[rows], g).reshape(len(of), m, g)
        for i in range(1, m):
            left = np.arange(len(of))
            for j in range(i):
                a, b = of[left] + i, of[left] + j
                may = components[a] != components[b]
                may[may] = np.minimum(held[left[may], i], held[left[may], j]).sum(axis=1, dtype=np.int64) >= needed(percent, sizes[a[may]], sizes[b[may]])
                yield a[may], b[may]
                if first_only:
                    left = left[~may]

    for m, g in np.unique(np.stack([counts, groups], axis=1), axis=0).tolist():
        of = starts[(counts == m) & (groups == g)]
        if m > FANOUT:
            for s in of.tolist():
                n, c = sizes[s : s + m], components[s : s + m]
                order = np.arange(m) if first_only else np.lexsort((n, c))
                for i, j in CountTree(unpacked(points[s : s + m], n, g), n, c, order).search(percent, first_only):
                    yield s + i, s + j
            continue
        step = max(1, CELLS_AT_ONCE // (m * g))
        for first in range(0, len(of), step):
            yield from leaves(of[first : first + step], m, g)


def tile_pairs(points: list[bytes], sizes: np.ndarray, components: np.ndarray, starts: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows (i, j), i < j, of all hits of :func:`tile_hits`."""
    hits = [np.zeros((2, 0), dtype=np.int64), *(np.sort(np.stack(h), axis=0) for h in tile_hits(points, sizes, components, starts, percent))]
    return tuple(np.concatenate(hits, axis=1))


TILE = ["key", "x", "y"]


def units(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """(rows, starts of units in them) of sorted batches; a unit is all rows with equal ``keys`` and is never cut."""
    held: pa.Table | None = None

    def starts(rows: pa.Table) -> np.ndarray:
        fresh = np.ones(len(rows), dtype=bool)
        columns = [np.asarray(rows.column(c).combine_chunks()) for c in keys]
        fresh[1:] = np.any([c[1:] != c[:-1] for c in columns], axis=0)
        return np.flatnonzero(fresh)

    for batch in batches:
        if batch.num_rows:
            rows = pa.Table.from_batches([batch])
            rows = rows if held is None else pa.concat_tables([held, rows])
            at = starts(rows)
            held = rows.slice(at[-1])
            if len(at) > 1:
                yield rows.slice(0, at[-1]), at[:-1]
    if held is not None:
        yield held, starts(held)


def together(dealt: DataFrame, keys: list[str], *within: str) -> DataFrame:
    """Rows of one unit in one task, side by side."""
    return dealt.repartition(*keys).sortWithinPartitions(*keys, *within)


def chunk_pairs(rows: DataFrame, node: str, chunks: Column) -> DataFrame:
    """Rows with (x, y): every two of a unit's chunks meet in one task, a row going to its own with each other."""
    dealt = rows.withColumn("own", F.pmod(F.xxhash64(node), chunks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), chunks - 1)))
    return dealt.withColumn("x", F.least("own", "other")).withColumn("y", F.greatest("own", "other")).drop("own", "other")


def tile_chunks() -> Column:
    return F.ceil(F.col("size") / UNIT).cast("int")


def columns_of(rows: pa.Table, *names: str) -> list[np.ndarray]:
    return [np.asarray(rows.column(c).combine_chunks()) for c in names]


def id_pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    ends = np.sort(np.stack([a, b]), axis=0)
    ends = np.unique(ends[:, ends[0] != ends[1]], axis=1)
    return pa.RecordBatch.from_arrays([pa.array(ends[0]), pa.array(ends[1])], ["a", "b"])


def first_pairs(members: DataFrame, percent: int) -> DataFrame:
    """(key, a, b), a < b: each member with the first hit of its search, within its tile or its chunk of one.

    ``members`` has (key, size, hub, node, n, point); the ``hub`` of a tile in chunks, its smallest id, is in all of them.
    """
    id_type = members.schema["node"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, starts in units(batches, ["key", "x"]):
            key, node, n = columns_of(rows, "key", "node", "n")
            found = [np.zeros((2, 0), dtype=np.int64), *map(np.stack, tile_hits(rows.column("point").to_pylist(), n, node, starts, percent, first_only=True))]
            i, j = np.concatenate(found, axis=1)  # at most one a member, whose hit is smaller as ids are in order
            yield pa.RecordBatch.from_arrays([pa.array(key[i]), pa.array(node[j]), pa.array(node[i])], ["key", "a", "b"])

    chunks = tile_chunks()
    everywhere = F.sequence(F.lit(0), chunks - 1)
    own = F.when(F.coalesce(F.col("node") == F.col("hub"), F.lit(False)), everywhere).otherwise(F.array(F.pmod(F.xxhash64("node"), chunks).cast("int")))
    dealt = members.withColumn("x", F.explode(own)).select("key", "x", "node", "n", "point")
    return together(dealt, ["key", "x"], "node").mapInArrow(run, f"key long, a {id_type}, b {id_type}")


def tree_pairs(members: DataFrame, percent: int) -> DataFrame:
    """All pairs (a, b), a < b, of different components within each tile, by the bound on their points.

    ``members`` has (key, node, component, n, point, size), size being the tile's. The result may grow with the
    square of a tile, so only :func:`join_links`, whose answer does too, asks for it.
    """
    id_type = members.schema["node"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, starts in units(batches, TILE):
            node, component, n = columns_of(rows, "node", "component", "n")
            for i, j in tile_hits(rows.column("point").to_pylist(), n, component, starts, percent):
                if len(i):
                    yield id_pairs(node[i], node[j])

    dealt = chunk_pairs(members, "node", tile_chunks()).select(*TILE, "node", "component", "n", "point")
    return together(dealt, TILE).mapInArrow(run, f"a {id_type}, b {id_type}").distinct()


def joined_ends(size: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest row that edges (i, j) connect each of ``size`` rows with."""
    label = np.arange(size)
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        np.minimum.at(new, label[i], low)
        np.minimum.at(new, label[j], low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


class Hits:
    """Hits of one tile: kept as pairs while few, from then on as the groups that they connect."""

    def __init__(self, size: int):
        self.size, self.total, self.parts, self.label = size, 0, [], None

    def add(self, i: np.ndarray, j: np.ndarray) -> None:
        self.total += len(i)
        self.parts.append((i, j))
        if self.total > PAIRS_A_MEMBER * self.size:
            i, j = (np.concatenate(x) for x in zip(*self.parts))
            if self.label is not None:
                i, j = np.concatenate([i, np.arange(self.size)]), np.concatenate([j, self.label])
            self.label, self.parts, self.total = joined_ends(self.size, i, j), [], 0

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        return tuple(np.concatenate(x) for x in zip(*self.parts)) if self.parts else (np.zeros(0, dtype=np.int64),) * 2


def mixed_hits(members: DataFrame, percent: int) -> DataFrame:
    """(a, b, g1, g2, weight): hits of different components in each tile, as pairs (a, b), or as groups: members a of (g1, g2).

    ``members`` as for :func:`tree_pairs`. A tile, or two chunks of one, gives at most ``PAIRS_A_MEMBER`` pairs or
    one group a member. A group is named by two hashes of its members, so the same group of several tiles is
    the same rows; ``weight`` is the number of shingles in it.
    """
    id_type = members.schema["node"].dataType.simpleString()
    names = ["a", "b", "g1", "g2", "weight"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, starts in units(batches, TILE):
            node, component, n = columns_of(rows, "node", "component", "n")
            ends, found = np.append(starts, len(rows)), {}
            for i, j in tile_hits(rows.column("point").to_pylist(), n, component, starts, percent):
                tile = np.searchsorted(starts, i, "right") - 1
                cuts = np.flatnonzero(np.diff(tile, prepend=-1))
                for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(tile)]):
                    t = int(tile[a])
                    found.setdefault(t, Hits(int(ends[t + 1] - ends[t]))).add(i[a:b] - ends[t], j[a:b] - ends[t])
            left, right = [np.zeros(0, dtype=node.dtype)], [np.zeros(0, dtype=node.dtype)]
            for t, hits in found.items():
                own, size = node[ends[t] : ends[t + 1]], n[ends[t] : ends[t + 1]]
                i, j = hits.pairs()
                left.append(own[i]), right.append(own[j])
                if hits.label is not None:
                    yield groups_of(own, size, hits.label)
            pairs = id_pairs(np.concatenate(left), np.concatenate(right))
            none = pa.nulls(len(pairs), pa.int64())
            yield pa.RecordBatch.from_arrays([*pairs.columns, none, none, none], names)

    def groups_of(own: np.ndarray, size: np.ndarray, label: np.ndarray) -> pa.RecordBatch:
        inside = np.bincount(label, minlength=len(own))[label] > 1
        own, size, label = own[inside], size[inside], np.unique(label[inside], return_inverse=True)[1]
        values = own.astype(np.int64).view(np.uint64)
        total = np.zeros((3, label.max() + 1), dtype=np.uint64)
        for row, part in zip(total, (mixed(values + np.uint64(1)), mixed(values + np.uint64(2)), size.astype(np.uint64))):
            np.add.at(row, label, part)
        g1, g2, weight = (pa.array(x[label].view(np.int64)) for x in total)
        return pa.RecordBatch.from_arrays([pa.array(own), pa.nulls(len(own), pa.array(own).type), g1, g2, weight], names)

    dealt = chunk_pairs(members, "node", tile_chunks()).select(*TILE, "node", "component", "n", "point")
    schema = f"a {id_type}, b {id_type}, g1 long, g2 long, weight long"
    return together(dealt, TILE).mapInArrow(run, schema).distinct()


def spanning_links(sets: list[np.ndarray], components: np.ndarray, percent: int) -> list[tuple[int, int]]:
    """Links (i, j) that join all linked components of some sets, from an inverted index of their elements.

    Members of small components are probed first; the search ends when those not yet probed are of one component.
    """
    sizes = np.array([len(x) for x in sets])
    at = np.concatenate([[0], np.cumsum(sizes)])
    held = np.unique(np.concatenate(sets), return_inverse=True)[1]
    owner = np.repeat(np.arange(len(sets)), sizes)[np.argsort(held, kind="stable")]
    many = np.bincount(held)
    begin = np.cumsum(many) - many
    component = np.unique(components, return_inverse=True)[1]
    left, links = np.ones(len(sets), dtype=bool), []
    for i in np.argsort(np.bincount(component)[component], kind="stable").tolist():
        if (component[left] == component[i]).all():
            break
        left[i] = False
        terms = held[at[i] : at[i + 1]]
        count = many[terms]
        index = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(begin[terms], count)
        shared = np.bincount(owner[index], minlength=len(sets))
        hits = np.flatnonzero((shared > 0) & (component != component[i]) & (100 * shared >= percent * (sizes + sizes[i] - shared)))
        for j in hits.tolist():
            if component[j] != component[i]:
                links.append((i, j))
                component[component == component[j]] = component[i]
    return links


def verified_groups(groups: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """Links (a, b) that join the linked components within each group; ``groups`` has (node, component, g1, g2, weight)."""
    id_type = groups.schema["node"].dataType.simpleString()
    keys = ["g1", "g2", "x", "y"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, nodes, components, sets = None, [], [], []

        def linked() -> pa.RecordBatch:
            links = np.array(spanning_links(sets, np.array(components), percent), dtype=np.int64).reshape(-1, 2)
            own = np.array(nodes)
            return id_pairs(own[links[:, 0]], own[links[:, 1]])

        for whole in batches:
            for start in range(0, whole.num_rows, 200):
                batch = whole.slice(start, 200)
                node, component = batch.column("node").to_pylist(), batch.column("component").to_pylist()
                key = list(zip(*(batch.column(c).to_pylist() for c in keys)))
                for first, h, _, sizes in sets_of(batch.column("text"), k):
                    at = np.concatenate([[0], np.cumsum(sizes)])
                    for i in range(len(sizes)):
                        if key[first + i] != last:
                            if len(nodes) > 1:
                                yield linked()
                            last, nodes, components, sets = key[first + i], [], [], []
                        nodes.append(node[first + i]), components.append(component[first + i]), sets.append(h[at[i] : at[i + 1]].copy())
        if len(nodes) > 1:
            yield linked()

    dealt = chunk_pairs(few(groups), "node", F.ceil(F.col("weight") / GROUP_SHINGLES).cast("int"))
    texts = docs.select(F.col("id").alias("node"), "text")
    rows = texts.join(dealt, "node").select(*keys, "node", "component", "text")
    return together(rows, keys, "node").mapInArrow(run, f"a {id_type}, b {id_type}").distinct()


def few(ids: DataFrame) -> DataFrame:
    """A written table, to be broadcast if its checked number of rows is small and shuffled otherwise."""
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def hot_tiles(table: DataFrame) -> DataFrame:
    """Keys of tiles with more than ``UNIT`` rows, from the counts of single tasks.

    A tile that is missed has fewer than ``LOCAL`` rows in every task, so it is small beside a task's input,
    whatever the table's size. Copies count here, so a tile may be called hot that has few members: it is
    counted otherwise then, and treated as what it is.
    """
    seen = table.where("often IS NOT NULL").select(F.explode("often").alias("o")).groupBy("o.key").agg(F.sum("o.seen").alias("seen"))
    return seen.where(F.col("seen") > UNIT).select("key")


def met_tiles(table: DataFrame, firsts: DataFrame, k: int, percent: int) -> DataFrame:
    """(key, node, size, hub) of the members of tiles with several ids, one tile for each set of members; written.

    ``firsts`` has the texts (id, text) of representatives. Hot tiles are counted by partial aggregation, all others
    side by side. ``hub`` is the smallest id, given for tiles in chunks only.
    """
    hot = save(hot_tiles(table), "hot-tiles")
    tiles = tile_table(firsts, k, percent).select("node", F.explode("keys").alias("key"))
    tile = Window.partitionBy("key")
    any_hot, cold = not hot.isEmpty(), tiles
    if any_hot:
        cold = tiles.join(few(hot), "key", "left_anti")
    figures = {"size": F.count("*").over(tile), "hub": F.min("node").over(tile), "last": F.max("node").over(tile), "mark": F.bit_xor(F.xxhash64("node")).over(tile)}
    met = cold.select("key", "node", *(c.alias(n) for n, c in figures.items())).where("hub < last")
    if any_hot:
        rows = save(tiles.join(few(hot), "key"), "hot-rows")
        counts = rows.groupBy("key").agg(F.count("*").alias("size"), F.min("node").alias("hub"), F.max("node").alias("last"), F.bit_xor(F.xxhash64("node")).alias("mark"))
        met = met.unionByName(rows.join(few(save(counts.where("hub < last"), "hot-counts")), "key").select(*met.columns))
    met = save(met, "tiles")
    sole = save(met.groupBy("size", "hub", "last", "mark").agg(F.min("key").alias("key")).select("key"), "sole-keys")
    hub = F.when(F.col("size") > UNIT, F.col("hub")).alias("hub")
    kept = save(met.join(few(sole), "key", "left_semi").select("key", "node", "size", hub), "sole-tiles")
    drop(met.sparkSession, met, hot, sole)
    return kept


def join_components(documents: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles, component_id) for every row; ids are whole numbers.

    Joins of tables of tiles are merge joins at any size; ids and keys are broadcast up to ``BROADCAST_IDS`` of them.
    """
    docs = documents.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    spark = documents.sparkSession
    table = save(point_table(docs, k, percent), "points")
    named = table.where("id IS NOT NULL AND n > 0")
    classes = save(named.groupBy("s1", "s2").agg(F.min("id").alias("id")), "classes")
    first_ids = save(classes.select("id").distinct(), "first-ids")
    met = met_tiles(table, docs.join(few(first_ids), "id", "left_semi"), k, percent)
    points = named.join(few(first_ids), "id", "left_semi").select(F.col("id").alias("node"), "n", "point")
    first_hits = save(first_pairs(met.hint("merge").join(points, "node"), percent), "first-hits")
    pairs = save(first_hits.select("a", "b").distinct(), "first-pairs")
    first_links = save(verified(pairs, docs, k, percent), "first-links")
    near = save(contract_components(first_links, "a", "b"), "near").select(F.col("id").alias("node"), F.col("label"))

    # A tile in which no member had a hit has none; of a tile in chunks that is not known yet.
    hit_keys = save(first_hits.select("key").distinct(), "hit-keys")
    again = met.where(f"size > 2 AND size <= {UNIT}").hint("merge").join(hit_keys, "key", "left_semi").unionByName(met.where(f"size > {UNIT}"))
    labelled = again.hint("merge").join(near, "node", "left").select("key", "node", "size", F.coalesce("label", "node").alias("component"))
    several = labelled.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("key")
    hits = save(mixed_hits(labelled.hint("merge").join(several, "key", "left_semi").hint("merge").join(points, "node"), percent), "hits")
    rest = save(hits.where("b IS NOT NULL").select("a", "b").hint("merge").join(pairs, ["a", "b"], "left_anti"), "all-pairs")
    later_links = save(verified(rest, docs, k, percent), "later-links")
    groups = hits.where("b IS NULL").select(F.col("a").alias("node"), "g1", "g2", "weight")
    grouped = save(groups.join(near, "node", "left").select("node", F.coalesce("label", "node").alias("component"), "g1", "g2", "weight"), "groups")
    group_links = save(verified_groups(grouped, docs, k, percent), "group-links")

    same_id = named.select("id", "s1", "s2").join(classes.select("s1", "s2", F.col("id").alias("rep")), ["s1", "s2"]).where("id <> rep").select(F.col("id").alias("a"), F.col("rep").alias("b")).distinct()
    several = named.groupBy("id").agg(F.min("s1").alias("lo"), F.max("s1").alias("hi")).where("lo < hi").select(F.col("id").alias("a"))
    doubled = same_id.join(several, "a", "left_semi")
    known = near.where("node <> label").select(F.col("node").alias("a"), F.col("label").alias("b"))
    whole = save(contract_components(known.unionByName(later_links).unionByName(group_links).unionByName(doubled), "a", "b"), "components")
    drop(spark, met, first_ids, first_hits, hit_keys, pairs, first_links, hits, rest, later_links, grouped, group_links)
    labels = classes.join(whole, "id", "left").select("s1", "s2", F.coalesce("label", "id").alias("component_id"))
    own = whole.select(F.col("id"), F.col("label").alias("own"))
    out = table.where("often IS NULL").select("id", "n", "s1", "s2").join(labels, ["s1", "s2"], "left").join(own, "id", "left")
    component = F.when(F.col("n") == 0, F.coalesce("own", "id")).otherwise(F.least("component_id", "own"))
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), component).alias("component_id"))


def join_links(documents: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(a, b), a < b: every verified link between class representatives, also within one component.

    Documents with equal sets are one class, named by its smallest id; each link is given once. The number
    of links, and so the cost, may grow with the square of a group of near copies.
    """
    docs = documents.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    table = save(point_table(docs, k, percent), "points")
    named = table.where("id IS NOT NULL AND n > 0")
    firsts = save(named.groupBy("s1", "s2").agg(F.min("id").alias("id")).select("id").distinct(), "first-ids")
    # Every member is a component of its own, so that no pair of a tile is passed over.
    met = met_tiles(table, docs.join(few(firsts), "id", "left_semi"), k, percent)
    points = named.join(few(firsts), "id", "left_semi").select(F.col("id").alias("node"), "n", "point")
    members = met.join(points, "node").withColumn("component", F.col("node"))
    pairs = save(tree_pairs(members, percent), "link-pairs")
    return verified(pairs, docs.join(few(firsts), "id", "left_semi"), k, percent)


def oracle(k: int, percent: int) -> str:
    """DuckDB SQL for :func:`join_components` over ``documents``: every pair that shares a shingle, counted."""
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    gram = " || ' ' || ".join(f"ws[i + {j}]" for j in range(k))
    return rf"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), '{upper}', '{upper.lower()}'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, g FROM (SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < {k} THEN [array_to_string(ws, ' ')]
  ELSE list_transform(range(1, len(ws) - {k - 2}), lambda i: {gram}) END) AS g FROM w)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * k >= {percent} * (a.n + b.n - k)),
e AS MATERIALIZED (SELECT x AS src, y AS dst FROM l UNION SELECT y, x FROM l),
d(id, c) USING KEY (id) AS (SELECT doc_id, doc_id FROM documents UNION
  SELECT t.id, min(t.c) FROM (SELECT e.dst AS id, d.c FROM d JOIN e ON e.src = d.id) t JOIN recurring.d r ON r.id = t.id WHERE t.c < r.c GROUP BY t.id)
SELECT d.id AS doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, d.c::BIGINT AS component_id FROM d LEFT JOIN n ON n.doc_id = d.id
"""
