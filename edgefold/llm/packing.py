"""Packing by concatenation and cutting.

All documents form one stream of ids, each document followed by the end id, and the stream is cut
every ``length`` ids, so no sequence but the last has padding. Two passes:

1. every task tokenises its rows once and writes (id, task, ids before this row in the task, ids);
2. the totals of the tasks - one number each - are summed in task order, which gives every document
   its place in the whole stream, and each document is cut where its place crosses a multiple of
   ``length``. The rows cut off are the boundary records: (document, start in it, length, sequence, offset).

Nothing but the totals is shuffled. The tokenised table lies in the shared folder, so a lost executor
is replaced by reading it again, and places never change between the passes.

Cases: null text is an empty document (its end id only); null ids and repeated rows are documents of
their own; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..runtime.scratch import save

#: How byte-level vocabularies split texts, and the characters on which every
#: implementation of that pattern agrees whatever its Unicode version.
BYTE_LEVEL_PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
AGREED = re.compile("[\t\n\r\x20-\x7e\xa1-ɏ‐-‧€]*")


class Encoder:
    """Ids of texts as the vocabulary file's library gives them, without added special tokens.

    A byte-level file whose merges are in id order is also run by a second, faster engine, built from
    that same file. Texts with an added token or a rare character, and those that the second engine can't
    split, go to the library itself. Tests hold both engines' ids against each other.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        with open(path, encoding="utf-8") as file:
            described = json.load(file)
        self.added = [t["content"] for t in described.get("added_tokens", [])]
        self.fast = self._engine(described)

    def _engine(self, described: dict):
        vocabulary, merges = described["model"].get("vocab"), described["model"].get("merges")
        before = described.get("pre_tokenizer") or {}
        plain = described["model"].get("type") == "BPE" and not described.get("normalizer") and before.get("type") == "ByteLevel"
        if not plain or before.get("add_prefix_space") or not before.get("use_regex", True):
            return None
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        if any(vocabulary.get(a + b) != 256 + i for i, (a, b) in enumerate(pairs)):
            return None
        import tiktoken

        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        letters = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
        ranks = {bytes(letters[c] for c in piece): rank for piece, rank in vocabulary.items() if piece not in self.added}
        return tiktoken.Encoding("from-file", pat_str=BYTE_LEVEL_PATTERN, mergeable_ranks=ranks, special_tokens={})

    def encode(self, text: str) -> np.ndarray:
        if self.fast is not None and AGREED.fullmatch(text) and not any(t in text for t in self.added):
            try:
                return self.fast.encode_to_numpy(text, disallowed_special=())
            except ValueError:  # its pattern engine gives up on a run of about a million white-space characters
                pass
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype=np.uint32)


def tokenise(docs: DataFrame, tokenizer_path: str, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """First pass: (id, task, before, n, ids) with ids as little-endian bytes of 2 or 4 each."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    id_type = source.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, task, before = Encoder(tokenizer_path), TaskContext.get().partitionId(), 0
        for batch in batches:
            for first in range(0, batch.num_rows, 500):
                part = batch.slice(first, 500)
                rows = [np.append(encoder.encode(t.as_py() or ""), end_id).astype("<u4") for t in part.column("text")]
                n = np.array([len(r) for r in rows], dtype=np.int64)
                places = before + np.cumsum(n) - n
                before += int(n.sum())
                small = [r.astype("<u2").tobytes() if r.max() < 65536 else r.tobytes() for r in rows]
                arrays = [part.column("id"), pa.array(np.full(len(n), task, dtype=np.int32)), pa.array(places), pa.array(n), pa.array(small, pa.binary())]
                yield pa.RecordBatch.from_arrays(arrays, ["id", "task", "before", "n", "ids"])

    return source.mapInArrow(run, f"id {id_type}, task int, before long, n long, ids binary")


def with_places(tokens: DataFrame) -> DataFrame:
    """Add ``place``: ids of the whole stream before each row. The totals are one row per task."""
    totals = tokens.groupBy("task").agg(F.sum("n").alias("total"))
    ahead = Window.orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("task", F.coalesce(F.sum("total").over(ahead), F.lit(0)).alias("base"))
    return tokens.join(F.broadcast(bases), "task").withColumn("place", F.col("base") + F.col("before"))


def cut_points(place: int, n: int, length: int) -> np.ndarray:
    """Starts of a document's pieces within it."""
    return np.concatenate([[0], np.arange(length - place % length, n, length)]).astype(np.int64)


def pack(docs: DataFrame, tokenizer_path: str, length: int = 2048, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Pieces (id, start, length, ids_crc32, doc_tokens, sequence_id, offset) and, if asked for, their ids.

    A reader joins the pieces of a sequence by offset and pads what is short - the last sequence at
    most - to ``length``, unless its size is a power of two already.
    """
    tokens = save(tokenise(docs, tokenizer_path, end_id, id_col, text_col), "tokens")
    placed = with_places(tokens).select("id", "n", "place", "ids")
    id_type = placed.schema["id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first in range(0, batch.num_rows, 500):
                part = batch.slice(first, 500)
                row, start, size, crc, seq, offset, pieces = [], [], [], [], [], [], []
                for i, (n, place, raw) in enumerate(zip(*(part.column(c).to_pylist() for c in ("n", "place", "ids")))):
                    ids = np.frombuffer(raw, "<u2" if len(raw) == 2 * n else "<u4").astype("<u4")
                    cuts = cut_points(place, n, length).tolist()
                    for a, b in zip(cuts, [*cuts[1:], n]):
                        data = ids[a:b].tobytes()
                        row.append(i), start.append(a), size.append(b - a), crc.append(zlib.crc32(data))
                        seq.append((place + a) // length), offset.append((place + a) % length)
                        if with_ids:
                            pieces.append(data)
                columns = [part.column("id").take(pa.array(row, pa.int64())), *(pa.array(x, pa.int64()) for x in (start, size, crc)), part.column("n").take(pa.array(row, pa.int64())), pa.array(seq, pa.int64()), pa.array(offset, pa.int64())]
                names = ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
                yield pa.RecordBatch.from_arrays(columns + [pa.array(pieces, pa.binary())] * with_ids, names + ["ids"] * with_ids)

    schema = f"id {id_type}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids binary" * with_ids
    return placed.mapInArrow(run, schema).withColumnRenamed("id", id_col)
