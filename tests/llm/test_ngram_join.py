"""The join against brute force: all pairs of sets, union-find over links."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest

from edgefold.llm import ngram_join
from edgefold.llm.hashing import SPACE, pieces, words

DOC = "doc_id long, text string, source string"


def sets_by_hand(rows, k):
    out = []
    for doc_id, text in rows:
        found = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        out.append((doc_id, {tuple(found[i : i + k]) for i in range(len(found) - k + 1)} or ({tuple(found)} if found else set())))
    return out


def brute(rows, k, percent):
    sets = sets_by_hand(rows, k)
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for i, (a, sa) in enumerate(sets):
        root(a) if a is not None else None
        for b, sb in sets[:i]:
            if a is not None and b is not None and sa and sb and 100 * len(sa & sb) >= percent * len(sa | sb):
                lo, hi = sorted((root(a), root(b)))
                parent[hi] = lo
    return sorted(((a, len(s), root(a) if a is not None else None) for a, s in sets), key=repr)


def joined(spark, rows, k, percent):
    docs = spark.createDataFrame([(a, t, "s") for a, t in rows], DOC).repartition(3)
    return sorted(map(tuple, ngram_join.join_components(docs, k, percent).collect()), key=repr)


def near_copies(seed=1):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(300)]
    rows, n = [], 0
    for size in (1, 2, 3, 5, 9, 12, 14, 20, 40, 90, 200, 400):
        for _ in range(3):
            base = rng.choices(vocabulary, k=size)
            rows.append((n, " ".join(base)))
            n += 1
            for edits in (0, 1, 1, 2, 3, 5, 8):
                copy = list(base)
                for _ in range(edits):
                    copy[rng.randrange(len(copy))] = rng.choice(vocabulary)
                if rng.random() < 0.4:
                    copy += rng.choices(vocabulary, k=rng.randint(1, 1 + size // 8))
                rows.append((n, " ".join(copy).upper() if rng.random() < 0.2 else " ".join(copy)))
                n += 1
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("k,percent", [(3, 90), (5, 80)])
def test_equals_brute_force_on_near_copies(spark, k, percent):
    rows = near_copies(percent)
    assert joined(spark, rows, k, percent) == brute(rows, k, percent)


def test_chain_of_links(spark):
    """Each text links to the next only; a star from the first would miss the later ones."""
    base = [f"c{i}" for i in range(100)]
    rows = [(i, " ".join(base[i * 2 :] + [f"d{j}" for j in range(i * 2)])) for i in range(12)]
    got = joined(spark, rows, 3, 90)
    assert got == brute(rows, 3, 90) and len({c for *_, c in got}) < 12


def test_hard_cases(spark):
    rows = [(1, None), (2, ""), (3, " \n"), (4, "one two"), (5, "ONE\ttwo"), (6, "one two three"), (None, "one two"), (7, "x " * 5000), (7, "one two"), (8, "x " * 6000), (9, "ÄÖ ä"), (10, "äÖ ä"), (5, "ONE\ttwo")]
    assert joined(spark, rows, 3, 90) == brute(rows, 3, 90)


def test_empty_table(spark):
    assert joined(spark, [], 3, 90) == []


def test_documents_equal_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    got = sorted(map(tuple, ngram_join.join_components(docs, 3, 90).collect()), key=repr)
    assert got == brute(rows, 3, 90)


def test_words_match_the_pattern():
    rng = random.Random(5)
    texts = ["".join(rng.choices("aBé \t\n\x0b\x0c\r\x1c\xa0,.", k=rng.randint(0, 30))) for _ in range(500)] + ["", None]
    count, same = 0, {}
    for first, data, bounds in pieces(pa.array(texts)):
        h, rows, _, _ = words(data, bounds, SPACE)
        for r in range(len(bounds) - 1):
            want = re.findall(r"[^\x20\x09-\x0D]+", (texts[first + r] or ""))
            got = h[rows == r].tolist()
            assert len(got) == len(want)
            for w, x in zip(want, got):
                w = re.sub("[A-Z]", lambda m: m[0].lower(), w)
                assert same.setdefault(w, x) == x
            count += 1
    assert count == len(texts) and len(set(same.values())) == len(same)


def sized_points(seed, count, low, high):
    """Sets of hashes, as near copies in pairs, with their packed points."""
    rng = np.random.default_rng(seed)
    sets = []
    for _ in range(count // 2):
        a = np.unique(rng.integers(0, 2**64, rng.integers(low, high), dtype=np.uint64))
        b = np.unique(np.concatenate([a[: int(len(a) * rng.uniform(0.8, 1))], rng.integers(0, 2**64, 2, dtype=np.uint64)]))
        sets += [a, b]
    sizes = np.array([len(s) for s in sets])
    groups = ngram_join.dimensions(sizes)
    points = [ngram_join.packed(np.bincount((s & np.uint64(g - 1)).astype(np.int64), minlength=g)) for s, g in zip(sets, groups.tolist())]
    return sets, sizes, points


def test_bounds_hold_at_any_number_of_groups():
    sets, sizes, points = sized_points(2, 60, 4, 900)
    for i in range(60):
        for j in range(60):
            shared = len(np.intersect1d(sets[i], sets[j]))
            for g in (64, int(min(ngram_join.dimensions(sizes[[i, j]])))):
                a, b = ngram_join.unpacked([points[i], points[j]], sizes[[i, j]], g)
                assert a.sum() == sizes[i] and np.minimum(a, b).sum() >= shared


@pytest.mark.parametrize("fanout", [2, 16, 1000])
def test_tiles_return_all_pairs_within_the_bound(fanout, monkeypatch):
    monkeypatch.setattr(ngram_join, "FANOUT", fanout)
    _, sizes, points = sized_points(3, 200, 20, 60)
    components, starts = np.arange(200) // 3, np.array([0, 1, 4, 20, 150])
    got = {tuple(p) for p in zip(*(x.tolist() for x in ngram_join.tile_pairs(points, sizes, components, starts, 80)))}
    held, want = ngram_join.unpacked(points, sizes, 64), set()
    for s, e in zip(starts, [*starts[1:], 200]):
        for i in range(s, e):
            for j in range(i + 1, e):
                if components[i] != components[j] and np.minimum(held[i], held[j]).sum() >= ngram_join.needed(80, sizes[i], sizes[j]):
                    want.add((i, j))
    assert got == want


def test_linked_pairs_share_a_tile():
    rng = np.random.default_rng(4)
    tops = ngram_join.scales(80)
    for size in (4, 5, 6, 9, 10, 20, 60, 300):
        for _ in range(40):
            whole = np.unique(rng.integers(0, 2**64, size, dtype=np.uint64))
            cut = int(len(whole) * 0.2)
            a, b = whole[: len(whole) - cut // 2], whole[cut - cut // 2 :]
            keys = []
            for s in (np.sort(a), np.sort(b)):
                keys.append(set(ngram_join.tile_keys(s, np.array([len(s)]), 80, tops)[1].tolist()))
            shared = len(np.intersect1d(a, b))
            if len(a) + len(b) > 2 * shared and 100 * shared >= 80 * (len(a) + len(b) - shared):
                assert keys[0] & keys[1]


def test_tables_of_few_words(spark):
    """Fewer words in all than a shingle has, in one task."""
    for rows in ([(1, "a")], [(1, "a b"), (2, "A B"), (3, None)], [(1, "a b c"), (2, "d")]):
        assert joined(spark, rows, 5, 80) == brute(rows, 5, 80)


def test_random_linked_pairs_share_a_tile():
    rng = np.random.default_rng(11)
    for percent in (80, 90):
        tops = ngram_join.scales(percent)
        for i in range(1500):
            whole = np.unique(rng.integers(0, 2**64, rng.integers(2, 120 if i % 3 else 24), dtype=np.uint64))
            gone = rng.permutation(len(whole))[: rng.integers(0, (100 - percent) * len(whole) // 100 + 1)]
            cut = rng.integers(0, len(gone) + 1)
            a, b = np.delete(whole, gone[:cut]), np.delete(whole, gone[cut:])
            if len(gone):
                first, second = (set(ngram_join.tile_keys(x, np.array([len(x)]), percent, tops)[1].tolist()) for x in (a, b))
                assert first & second
