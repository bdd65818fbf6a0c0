"""Vectorised hashing of words and shingles over the raw bytes of Arrow string columns.

A word's hash is a polynomial of its bytes, taken from running sums over the whole buffer, so no
string object is made; a finalising mix spreads it over 64 bits. Buffers are cut at row ends so that a
piece has about ``PIECE`` bytes (a longer row is a piece of its own).
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

PIECE = 1_000_000
_BASE = np.uint64(0x9E3779B97F4A7C15)
_rng = np.random.Generator(np.random.PCG64(20240117))
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_EXACT = _BYTE.copy()
_BYTE[65:91] = _BYTE[97:123]  # A-Z hash as a-z
_SHIFTS = _rng.integers(1, 2**63, 64, dtype=np.uint64) | np.uint64(1)
#: Separators: ASCII white space (x20, x09-x0D), or every ASCII character but letters and digits.
SPACE = np.isin(np.arange(256), [32, 9, 10, 11, 12, 13])
PUNCTUATION = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def mixed(x: np.ndarray) -> np.ndarray:
    """Finalise 64-bit values so that every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=2)
def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    inverse = np.uint64(pow(int(_BASE), -1, 2**64))
    return tuple(np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, b, dtype=np.uint64)])) for b in (_BASE, inverse))


def pieces(column: pa.Array, lowered: bool = False) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, row bounds in them) for runs of rows; null rows are empty. Only a run is copied at a time."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(column), 0), dtype=np.int64)
    group = (np.cumsum(sizes) - sizes) // PIECE
    edges = [*np.flatnonzero(np.diff(group, prepend=-1)).tolist(), len(column)]
    for a, b in zip(edges[:-1], edges[1:]):
        run = pc.fill_null(column.slice(a, b - a).cast(pa.large_string()), "")
        run = pc.utf8_lower(run) if lowered else run
        bounds = np.frombuffer(run.buffers()[1], np.int64)[run.offset : run.offset + len(run) + 1]
        data = np.frombuffer(run.buffers()[2] or b"", np.uint8)
        yield a, data[bounds[0] : bounds[-1]], bounds - bounds[0]


def words(data: np.ndarray, bounds: np.ndarray, separators: np.ndarray = SPACE, exact: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash, row, start, end) of every word, in order; letters A-Z hash as a-z unless ``exact``."""
    n = len(data)
    if n == 0:
        none = np.zeros(0, dtype=np.int64)
        return none.astype(np.uint64), none, none, none
    solid = ~separators[data]
    edge = np.zeros(n + 1, dtype=bool)
    edge[bounds] = True
    begins = solid.copy()
    begins[1:] &= ~solid[:-1] | edge[1:n]
    ends = solid.copy()
    ends[:-1] &= ~solid[1:] | edge[1:n]
    start, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    size = 1 << max(16, int(n - 1).bit_length())
    power, inverse = _powers(size)
    sums = np.concatenate([[np.uint64(0)], np.cumsum((_EXACT if exact else _BYTE)[data] * power[:n])])
    hashes = mixed((sums[end] - sums[start]) * inverse[start] + (end - start).astype(np.uint64))
    return hashes, np.searchsorted(bounds, start, "right") - 1, start, end


def shingles(hashes: np.ndarray, rows: np.ndarray, n_rows: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, row, count per row): every row's distinct k-word shingles, sorted by hash within the row.

    A row of 1 to k-1 words has its whole sequence as its only shingle; a row without words has none.
    """
    per_row = np.bincount(rows, minlength=n_rows)
    first = np.concatenate([[0], np.cumsum(per_row)])
    sums = np.zeros(max(0, len(hashes) - k + 1), dtype=np.uint64)
    for j in range(k):
        sums += mixed(hashes[j : j + len(sums)] * _SHIFTS[j]) * _SHIFTS[32 + j]
    inside = rows[: len(sums)] == rows[k - 1 :] if len(sums) else np.zeros(0, dtype=bool)
    full, full_rows = mixed(sums[inside]), rows[: len(sums)][inside]
    short = np.flatnonzero((per_row > 0) & (per_row < k))
    extra = np.zeros(len(short), dtype=np.uint64)
    for i, r in enumerate(short):  # one-element arrays wrap around without warnings
        own = hashes[first[r] : first[r + 1]]
        value = np.full(1, len(own), dtype=np.uint64)
        for j in range(len(own)):
            value = value * np.uint64(31) + own[j : j + 1] * _SHIFTS[16 + j % 16]
        extra[i] = value[0]
    if len(short):
        full, full_rows = np.concatenate([full, mixed(extra)]), np.concatenate([full_rows, short])
        order = np.argsort(full_rows, kind="stable")
        full, full_rows = full[order], full_rows[order]
    counts = np.bincount(full_rows, minlength=n_rows)
    at = np.concatenate([[0], np.cumsum(counts)])
    for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
        if b - a > 1:
            full[a:b].sort()
    fresh = np.ones(len(full), dtype=bool)
    fresh[1:] = (full[1:] != full[:-1]) | (full_rows[1:] != full_rows[:-1])
    full, full_rows = full[fresh], full_rows[fresh]
    return full, full_rows, np.bincount(full_rows, minlength=n_rows)
