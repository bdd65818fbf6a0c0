"""Vertex ids: raw keys in graphs of one kind, key * 16 + kind where kinds meet."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Kinds of entities (fixed values).
KINDS = {"customer": 0, "supplier": 1, "part": 2, "nation": 3, "user": 4, "document": 5, "line": 6, "page": 7, "path": 8, "turn": 9, "vector": 10, "order": 11}


def typed(key: Column | str, kind: str) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * 16 + KINDS[kind]


def text_key(text: Column) -> Column:
    """56 bits of a digest of a string; dictionary ids replace it where collisions would matter."""
    return F.conv(F.substring(F.md5(text), 1, 14), 16, 10).cast("long")


def mix(x: Column | str) -> Column:
    """Arithmetic scrambling that stays in 64 bits and is the same in every SQL engine."""
    return ((F.col(x) if isinstance(x, str) else x) % 1000003 * 7919 + 104729) % 1000003


def mix_sql(x: str) -> str:
    return f"((({x}) % 1000003 * 7919 + 104729) % 1000003)"
