"""Benchmark decontamination: BM25 over an inverted index of the items, pruned by block maxima.

The index holds the benchmark, not the corpus: items are sorted by length and grouped in blocks, blocks
in super-blocks. A posting keeps a term's BM25 share of its item's own score, so that an item that lies
whole in a passage scores 1 whatever its length, and one limit fits all items. For every group the
largest share of each term over its members bounds what any member can score.

Training texts are the queries. Every super-block has its own passage length, twice its longest item
with half of that as stride, so any run of an item's length lies in one passage. Per super-block

1. running sums of term bounds over a text bound all passages at once, and for those left the sums over
   distinct terms do; passages below the limit end here;
2. the bounds of each block over the passage's distinct terms drop most blocks;
3. items of the blocks left are scored in full, and all at or above the limit are retrieved;
4. a retrieved item is verified: the share of word trigrams of its question part and of its answer part
   that the passage holds must reach their limits.

The index is broadcast in shards of at most ``SHARD`` items. The corpus is read and hashed once: a task holds the
hashes of about ``HELD`` bytes of texts and takes one shard after another into memory for them, so neither
the number of passes nor a task's memory grows with the benchmark. Items, mean length and document frequencies
are the whole benchmark's in every shard. Nothing is shuffled.

A pivot over term-ordered cursors, as a query of few terms against millions of documents needs, skips blocks whose
maxima can't reach the limit. Here a query has hundreds of terms and a super-block a dozen blocks, so the maxima of all
its blocks are summed at once, which leaves the same blocks and no others.

Items are (id, text) or have question and answer columns; of a plain text the last sentence is the
answer part. Words are runs of letters and digits, lower-cased. Cases: null, empty and wordless texts
and items match nothing; null ids are kept; repeated rows and items give a row each; empty tables give
empty results; texts of any length are searched whole; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hashing import PUNCTUATION, pieces, shingles, words

K1, B = 1.2, 0.75
LIMIT, QUESTION_SHARE, ANSWER_SHARE = 0.6, 0.6, 0.5
GRAM, BLOCK, SUPER, SHARD = 3, 16, 6, 1024
#: Bytes of text whose hashes a task holds for all shards, and terms of windows that are sorted at once.
HELD, CELLS_AT_ONCE = 8_000_000, 500_000
SENTENCE = re.compile(r"(?<=[.!?])\s+|\n+")


def word_hashes(texts: list[str]) -> list[np.ndarray]:
    out = [np.zeros(0, dtype=np.uint64)] * len(texts)
    for first, data, bounds in pieces(pa.array(texts, pa.large_string()), lowered=True):
        hashes, rows, _, _ = words(data, bounds, PUNCTUATION)
        for r in range(len(bounds) - 1):
            out[first + r] = hashes[np.searchsorted(rows, r) : np.searchsorted(rows, r + 1)]
    return out


def parts(text: str) -> tuple[str, str]:
    """Question and answer part of a plain item: the last sentence answers; one sentence alone is cut at three quarters."""
    sentences = [s for s in SENTENCE.split(text) if re.search(r"\w", s)]
    if len(sentences) > 1:
        return " ".join(sentences[:-1]), sentences[-1]
    tokens = text.split()
    cut = max(1, len(tokens) * 3 // 4)
    return " ".join(tokens[:cut]), " ".join(tokens[cut:])


def grams(tokens: np.ndarray, size: int = GRAM) -> np.ndarray:
    return shingles(tokens, np.zeros(len(tokens), dtype=np.int64), 1, size)[0]


def held(part: np.ndarray, passage: np.ndarray, known: dict[int, np.ndarray]) -> float:
    """Share of a part's word n-grams that the passage holds; a part of fewer words is one gram of its size."""
    size = min(GRAM, len(part))
    if not size:
        return 1.0
    if size not in known:
        known[size] = grams(passage, size)
    return float(np.isin(grams(part, size), known[size]).mean())


class Group:
    """A super-block: its items' shares per term, and the maxima of its blocks and of itself."""

    def __init__(self, members: list[int], shares: list[dict[int, float]], lengths: np.ndarray, n_terms: int):
        self.members = np.array(members)
        terms = np.array(sorted(set().union(*(shares[i] for i in members))), dtype=np.int64)
        self.slot = np.full(n_terms + 1, -1, dtype=np.int32)
        self.slot[terms] = np.arange(len(terms))
        self.shares = np.zeros((len(terms), len(members)), dtype=np.float32)
        for j, i in enumerate(members):
            self.shares[self.slot[list(shares[i])], j] = list(shares[i].values())
        starts = np.arange(0, len(members), BLOCK)
        self.blocks = np.maximum.reduceat(self.shares, starts, axis=1)
        self.padded = np.vstack([self.blocks, np.zeros((1, len(starts)), dtype=np.float32)])  # slot -1 is no term
        self.bound = np.zeros(n_terms + 1, dtype=np.float32)
        self.bound[terms] = self.blocks.max(axis=1)
        self.length = 2 * int(max(lengths[i] for i in members))


class Statistics:
    """Figures of a whole benchmark that its items' weights come from: items with words, their mean length, and each word's items."""

    def __init__(self) -> None:
        self.items = self.total = 0
        self.terms, self.holders = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)

    def add(self, items: list[tuple[int, str, str]]) -> None:
        tokens = [np.concatenate(x) for x in zip(*(word_hashes([i[part] or "" for i in items]) for part in (1, 2)))]
        self.items += sum(len(t) > 0 for t in tokens)
        self.total += sum(map(len, tokens))
        seen, counts = np.unique(np.concatenate([*map(np.unique, tokens), np.zeros(0, dtype=np.uint64)]), return_counts=True)
        terms = np.union1d(self.terms, seen)
        holders = np.zeros(len(terms), dtype=np.int64)
        holders[np.searchsorted(terms, self.terms)] = self.holders
        holders[np.searchsorted(terms, seen)] += counts
        self.terms, self.holders = terms, holders


class Index:
    """BM25 index of benchmark items given as (id, question, answer), weighted by figures of the whole benchmark."""

    def __init__(self, items: list[tuple[int, str, str]], known: Statistics | None = None):
        if known is None:
            known = Statistics()
            known.add(items)
        self.ids = [i for i, _, _ in items]
        question, answer = word_hashes([q or "" for _, q, _ in items]), word_hashes([a or "" for _, _, a in items])
        tokens = [np.concatenate(x) for x in zip(question, answer)]
        self.question, self.answer = question, answer
        self.vocabulary = np.unique(np.concatenate([*tokens, np.zeros(0, dtype=np.uint64)]))
        n_terms, lengths = len(self.vocabulary), np.array([len(t) for t in tokens])
        full = np.flatnonzero(lengths > 0)
        counts = {int(i): np.unique(np.searchsorted(self.vocabulary, tokens[i]), return_counts=True) for i in full}
        holders = known.holders[np.searchsorted(known.terms, self.vocabulary)]
        idf, mean = np.log1p((known.items - holders + 0.5) / (holders + 0.5)), known.total / max(1, known.items)
        shares: list[dict[int, float]] = [{} for _ in items]
        for i, (terms, tf) in counts.items():
            weight = idf[terms] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * lengths[i] / mean))
            shares[i] = dict(zip(terms.tolist(), (weight / weight.sum()).tolist()))
        order = full[np.argsort(lengths[full], kind="stable")].tolist()
        size = -(-len(order) // SUPER) if order else 1
        self.groups = [Group(order[a : a + size], shares, lengths, n_terms) for a in range(0, len(order), size)]

    def search(self, hashes: np.ndarray, rows: np.ndarray, n_rows: int, limit: float) -> list[tuple[int, int, float, float, float]]:
        """(row, item, score, question share, answer share) of verified pairs, the best passage of each."""
        n_terms, best = len(self.vocabulary), {}
        if not n_terms or not len(hashes):
            return []
        term = np.searchsorted(self.vocabulary, hashes)
        term[term == n_terms] = 0
        term = np.where(self.vocabulary[term] == hashes, term, n_terms)
        per_row = np.bincount(rows, minlength=n_rows)
        first = np.concatenate([[0], np.cumsum(per_row)])
        for group in self.groups:
            sums = np.concatenate([[0.0], np.cumsum(group.bound[term], dtype=np.float64)])
            stride = group.length // 2
            n_windows = np.where(per_row > 0, np.maximum(1, -(-(per_row - group.length) // stride) + 1), 0)
            row = np.repeat(np.arange(n_rows), n_windows)
            nth = np.arange(len(row)) - np.repeat(np.cumsum(n_windows) - n_windows, n_windows)
            a = first[row] + nth * stride
            b = np.minimum(a + group.length, first[row + 1])
            for w in self._distinct(group, term, a, b, np.flatnonzero(sums[b] - sums[a] >= limit - 1e-6), limit):
                self._passage(group, int(row[w]), term[a[w] : b[w]], hashes[a[w] : b[w]], limit, best)
        return [(r, i, *v) for (r, i), v in sorted(best.items())]

    def _distinct(self, group: Group, term: np.ndarray, a: np.ndarray, b: np.ndarray, windows: np.ndarray, limit: float) -> list[int]:
        """The windows for which the bounds of some block over the distinct terms reach the limit."""
        left, place = [], np.arange(group.length)
        step = max(1, CELLS_AT_ONCE // group.length)
        for at in range(0, len(windows), step):
            w = windows[at : at + step]
            index = a[w][:, None] + place
            terms = np.where(index < b[w][:, None], term[np.minimum(index, len(term) - 1)], len(self.vocabulary))
            terms.sort(axis=1)
            bounds = group.bound[terms]
            terms[:, 1:][terms[:, 1:] == terms[:, :-1]] = len(self.vocabulary)
            bounds = np.where(terms < len(self.vocabulary), bounds, 0)
            may = bounds.sum(axis=1, dtype=np.float64) >= limit - 1e-5
            w, terms = w[may], terms[may]
            blocks = group.padded[group.slot[terms]].sum(axis=1, dtype=np.float64)
            left += w[(blocks >= limit - 1e-5).any(axis=1)].tolist()
        return left

    def _passage(self, group: Group, row: int, term: np.ndarray, hashes: np.ndarray, limit: float, best: dict) -> None:
        slots = np.unique(group.slot[term])
        slots = slots[slots >= 0]
        blocks = np.flatnonzero(group.blocks[slots].sum(axis=0) >= limit - 1e-4)
        if not len(blocks):
            return
        columns = np.concatenate([np.arange(b * BLOCK, min((b + 1) * BLOCK, len(group.members))) for b in blocks])
        scores = group.shares[np.ix_(slots, columns)].sum(axis=0, dtype=np.float64)
        known: dict[int, np.ndarray] = {}
        for j in np.flatnonzero(scores >= limit - 1e-6):
            item = int(group.members[columns[j]])
            q, a = held(self.question[item], hashes, known), held(self.answer[item], hashes, known)
            if q >= QUESTION_SHARE and a >= ANSWER_SHARE:
                found = (round(float(scores[j]), 4), round(q, 4), round(a, 4))
                best[row, item] = max(found, best.get((row, item), (0.0, 0.0, 0.0)))


def shards(benchmark: DataFrame, item_col: str, text_col: str, question_col: str | None, answer_col: str | None) -> Iterator[Index]:
    """Indexes of at most ``SHARD`` items each; the items of one shard at a time are on the driver.

    A first pass over the items takes the figures of the whole benchmark, a second one builds the indexes.
    """
    texts = [F.col(question_col), F.col(answer_col)] if question_col else [F.col(text_col), F.lit(None)]
    items = benchmark.select(F.col(item_col).alias("i"), *(t.cast("string").alias(n) for t, n in zip(texts, "qa")))

    def batches() -> Iterator[list[tuple[int, str, str]]]:
        batch: list[tuple[int, str, str]] = []
        for r in items.orderBy("i", "q", "a").toLocalIterator():
            batch.append((r["i"], r["q"], r["a"]) if question_col else (r["i"], *parts(r["q"] or "")))
            if len(batch) == SHARD:
                yield batch
                batch = []
        if batch:
            yield batch

    known = Statistics()
    for batch in batches():
        known.add(batch)
    for batch in batches():
        yield Index(batch, known)


def small_batches(batches: Iterator[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield from (batch.slice(a, rows) for a in range(0, batch.num_rows, rows))


def hits(batches: Iterator[pa.RecordBatch], shared: list, limit: float) -> Iterator[tuple[pa.RecordBatch, list[tuple]]]:
    """(batch, its hits as (row, item id, score, question share, answer share)) over all shards of the index."""
    held: list[tuple[pa.RecordBatch, list, list]] = []
    size = 0

    def searched() -> Iterator[tuple[pa.RecordBatch, list[tuple]]]:
        for shard in shared:
            index = shard.value
            for _, runs, found in held:
                for first, hashes, rows, n_rows in runs:
                    found += [(first + h[0], index.ids[h[1]], *h[2:]) for h in index.search(hashes, rows, n_rows, limit)]
            if len(shared) > 1:
                vars(shard).pop("_value", None)
        yield from ((batch, found) for batch, _, found in held)
        held.clear()

    for batch in small_batches(batches):
        runs = []
        for first, data, bounds in pieces(batch.column("text"), lowered=True):
            runs.append((first, *words(data, bounds, PUNCTUATION)[:2], len(bounds) - 1))
            size += len(data)
        held.append((batch, runs, []))
        if size >= HELD or len(shared) < 2:
            yield from searched()
            size = 0
    yield from searched()


def contaminated(
    docs: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    question_col: str | None = None,
    answer_col: str | None = None,
    limit: float = LIMIT,
) -> DataFrame:
    """(id, item_id, score, question_share, answer_share): every verified pair of a text and an item."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    id_type, item_type = source.schema["id"].dataType.simpleString(), benchmark.schema[item_col].dataType.simpleString()
    context = docs.sparkSession.sparkContext
    shared = [context.broadcast(index) for index in shards(benchmark, item_col, item_text_col, question_col, answer_col)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, found in hits(batches, shared, limit):
            if found:
                row, item, *figures = (list(x) for x in zip(*found))
                ids = batch.column("id").take(pa.array(row, pa.int64()))
                items = pa.array(item) if any(i is not None for i in item) else pa.nulls(len(item), pa.int64())
                yield pa.RecordBatch.from_arrays([ids, items, *(pa.array(x, pa.float64()) for x in figures)], ["id", "item", "score", "question_share", "answer_share"])

    found = source.mapInArrow(run, f"id {id_type}, item {item_type}, score double, question_share double, answer_share double")
    return found.withColumnRenamed("id", id_col).withColumnRenamed("item", item_col)


def clean(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", limit: float = LIMIT) -> DataFrame:
    """The rows of ``docs``, all columns, whose text holds no verified item; ids play no part, so they may be null or repeated."""
    source = docs.select(F.struct(*docs.columns).alias("row"), F.col(text_col).cast("string").alias("text"))
    context = docs.sparkSession.sparkContext
    shared = [context.broadcast(index) for index in shards(benchmark, item_col, item_text_col, None, None)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, found in hits(batches, shared, limit):
            kept = np.ones(batch.num_rows, dtype=bool)
            kept[[row for row, *_ in found]] = False
            yield batch.select(["row"]).filter(pa.array(kept))

    return source.mapInArrow(run, f"row {source.schema['row'].dataType.simpleString()}").select("row.*")
