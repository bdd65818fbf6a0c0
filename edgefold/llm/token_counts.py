"""Token counts without token ids.

A tokenizer that drops white space never lets a piece cross it, so the number of tokens of a text is the sum
over its white-space-delimited pre-tokens of the pieces in each:

1. *Distinct pre-tokens.* Every task gives its distinct pre-tokens with their occurrences; grouped over the corpus
   they are the vocabulary, and the library counts the pieces of each of its members once.
2. *Frequencies.* A second pass has, per document, the frequency of each pre-token. Those of the most
   frequent pre-tokens - at most ``FREQUENT`` of them, whatever the corpus, broadcast as two arrays - are
   multiplied with their pieces and summed on the spot, so that a word that is in every document is never shuffled.
3. *Join and sum.* The frequencies of all other pre-tokens are joined to the vocabulary by hash and summed per document.

The second pass writes its rows, numbered, so that a lost executor changes no number. Pre-tokens compare by
64-bit hashes of their exact bytes. A tokenizer for which white space matters (found by probing it, see
``cuts_at_space``) gets whole texts instead, and its tokens are counted text by text.

Files ending in .json are read by the tokenizers library, .model by sentencepiece.

Cases: null text counts as empty (0 bytes, 0 tokens); null ids are kept; repeated rows are counted
each; texts may be of any length; an empty table gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..runtime.scratch import save
from .hashing import pieces, words

#: Most pre-tokens whose counts are broadcast, and most that a task holds before it gives them on.
FREQUENT, HELD = 500_000, 500_000
#: What probes put on both sides of white space, and the white space that delimits pre-tokens.
BESIDE, DELIMITERS = ("a", "B", "s", "7", ".", "'", "'s", "-", "é", "中", "<", ">"), "\t\n\x0b\x0c\r "


@lru_cache(maxsize=4)
def counter(path: str) -> tuple[Callable[[list[str]], list[int]], bool]:
    """(function that counts the tokens of texts, whether texts can be cut at white space)."""
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(model.encode(t)) for t in texts], False
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(path)
    library.no_truncation()
    library.no_padding()
    return lambda texts: [len(x) for x in library.encode_batch_fast(texts, add_special_tokens=False)], cuts_at_space(library)


def cuts_at_space(library) -> bool:
    """Whether tokens on both sides of white space are those of the sides alone, and no added token takes white space in."""
    if any(t.lstrip or t.rstrip or re.search(r"\s", t.content) for t in library.get_added_tokens_decoder().values()):
        return False
    ids = lambda text: library.encode(text, add_special_tokens=False).ids
    alone = {x: ids(x) for x in BESIDE}
    gaps = [*DELIMITERS, *(a + b for a, b in product(DELIMITERS, repeat=2))]
    return all(ids(x + gap + y) == alone[x] + alone[y] for x, y in product(BESIDE, repeat=2) for gap in gaps) and not any(map(ids, gaps))


def vocabulary(texts: DataFrame, path: str) -> DataFrame:
    """(hash, seen, pieces) of every distinct pre-token of the corpus, its pieces counted once."""

    def distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, seen, held = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64), []

        def given() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(known.view(np.int64)), pa.array(held, pa.string()), pa.array(seen)], ["hash", "word", "seen"])

        for batch in batches:
            for _, data, bounds in pieces(batch.column("text")):
                hashes, _, start, end = words(data, bounds, exact=True)
                own, first, count = np.unique(hashes, return_index=True, return_counts=True)
                at = np.searchsorted(known, own)
                fresh = np.ones(len(own), dtype=bool)
                inside = at < len(known)
                fresh[inside] = known[at[inside]] != own[inside]
                seen[at[~fresh]] += count[~fresh]
                if fresh.any():
                    raw = data.tobytes()
                    new = [raw[a:b].decode() for a, b in zip(start[first[fresh]].tolist(), end[first[fresh]].tolist())]
                    known, seen, held = np.concatenate([known, own[fresh]]), np.concatenate([seen, count[fresh]]), held + new
                    order = np.argsort(known, kind="stable")
                    known, seen, held = known[order], seen[order], [held[i] for i in order.tolist()]
                if len(known) > HELD:
                    yield given()
                    known, seen, held = known[:0], seen[:0], []
        yield given()

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, _ = counter(path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("hash"), batch.column("seen"), pa.array(count(batch.column("word").to_pylist()), pa.int64())], ["hash", "seen", "pieces"])

    found = texts.select("text").mapInArrow(distinct, "hash long, word string, seen long")
    once = found.groupBy("hash").agg(F.min("word").alias("word"), F.sum("seen").alias("seen"))
    return once.mapInArrow(counted, "hash long, seen long, pieces long")


def frequent(known: DataFrame, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, pieces) of the most frequent pre-tokens, ordered by hash; at most ``most`` of them.

    Their least frequency is a power of two, taken from the numbers of pre-tokens between such powers.
    """
    power = F.floor(F.log2("seen")).cast("int")
    sizes = {r["power"]: r["count"] for r in known.groupBy(power.alias("power")).count().collect()}
    least, total = 64, 0
    for p in sorted(sizes, reverse=True):
        if (total := total + sizes[p]) > most:
            break
        least = p
    rows = known.where(power >= least).select("hash", "pieces").toArrow()
    hashes, counts = (np.asarray(rows.column(c).combine_chunks()) for c in ("hash", "pieces"))
    order = np.argsort(hashes.view(np.uint64), kind="stable")
    return hashes.view(np.uint64)[order], counts[order]


def count_tokens(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048) -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of every row; see the module's text for the method and cases."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    id_type = source.schema["id"].dataType.simpleString()
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")
    shown = [F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit")]
    if not counter(tokenizer_path)[1]:
        return whole_texts(source.select("id", size, "text"), tokenizer_path, id_type).select(*shown)

    known = save(vocabulary(source, tokenizer_path), "vocabulary")
    shared = docs.sparkSession.sparkContext.broadcast(frequent(known, FREQUENT))
    rare_type = pa.list_(pa.struct([("hash", pa.int64()), ("times", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often, count = shared.value
        number = TaskContext.get().partitionId() << 33
        for batch in batches:
            for first, data, bounds in pieces(batch.column("text")):
                hashes, rows, _, _ = words(data, bounds, exact=True)
                n = len(bounds) - 1
                at = np.minimum(np.searchsorted(often, hashes), max(0, len(often) - 1))
                common = often[at] == hashes if len(often) else np.zeros(len(hashes), dtype=bool)
                sums = np.zeros(n, dtype=np.int64)
                np.add.at(sums, rows[common], count[at[common]])
                own, row = hashes[~common], rows[~common]
                order = np.lexsort((own, row))
                own, row = own[order], row[order]
                starts = np.flatnonzero(np.concatenate([np.ones(len(own[:1]), dtype=bool), (own[1:] != own[:-1]) | (row[1:] != row[:-1])]))
                times = np.diff(np.append(starts, len(own)))
                rare = pa.StructArray.from_arrays([pa.array(own[starts].view(np.int64)), pa.array(times.astype(np.int64))], ["hash", "times"])
                lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(row[starts], np.arange(n + 1)).astype(np.int32)), rare)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(number, number + n)), batch.column("id").slice(first, n), pa.array(np.diff(bounds).astype(np.int64)), pa.array(sums), lists.cast(rare_type)], ["number", "id", "n_bytes", "common", "rare"])
                number += n

    schema = f"number long, id {id_type}, n_bytes long, common long, rare array<struct<hash:long,times:long>>"
    rows = save(source.mapInArrow(run, schema), "frequencies")
    pairs = rows.select("number", F.explode("rare").alias("r")).select("number", "r.hash", "r.times")
    sums = pairs.join(known.select("hash", "pieces"), "hash").groupBy("number").agg(F.sum(F.col("times") * F.col("pieces")).alias("others"))
    out = rows.drop("rare").join(sums, "number", "left").withColumn("n_tokens", F.col("common") + F.coalesce("others", F.lit(0)))
    return out.select(*shown)


def whole_texts(source: DataFrame, path: str, id_type: str) -> DataFrame:
    """(id, n_bytes, n_tokens) with every text given to the library as it is."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, _ = counter(path)
        for batch in batches:
            for first in range(0, batch.num_rows, 200):
                part = batch.slice(first, 200)
                tokens = count([t or "" for t in part.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("n_bytes"), pa.array(tokens, pa.int64())], ["id", "n_bytes", "n_tokens"])

    return source.mapInArrow(run, f"id {id_type}, n_bytes long, n_tokens long")
