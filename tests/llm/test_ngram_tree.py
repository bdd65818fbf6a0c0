"""The tree search gives every link, and no step's rows grow with the square of a group."""

import random

import numpy as np
import pytest

from edgefold.llm import ngram_join

from .test_ngram_join import brute, joined, sized_points


def family(members, words, edits, seed=1):
    """Texts of one base, each with its own words replaced: near each other, all pairs about as far apart."""
    rng, base = random.Random(seed), [f"b{i}" for i in range(words)]
    rows = []
    for m in range(members):
        own = list(base)
        for place in rng.sample(range(words), edits):
            own[place] = f"m{m}x{place}"
        rows.append((m, " ".join(own)))
    return rows


@pytest.mark.parametrize("edits", [1, 3, 4, 6])
def test_families_equal_brute_force(spark, edits):
    rows = family(60, 120, edits)
    assert joined(spark, rows, 5, 80) == brute(rows, 5, 80)


def counted(monkeypatch, *names):
    """Rows that the named steps give, by name."""
    seen = {}
    for name in names:
        step = getattr(ngram_join, name)

        def run(*args, step=step, name=name):
            out = step(*args)
            seen[name] = out.count()
            return out

        monkeypatch.setattr(ngram_join, name, run)
    return seen


def test_rows_of_an_unlinked_family_grow_with_its_members(spark, monkeypatch):
    """All pairs of a tile pass the bound and none links: the rows of a tile stay within a multiple of its members."""
    seen, figures = counted(monkeypatch, "first_pairs", "mixed_hits"), []
    for members in (100, 200):
        docs = spark.createDataFrame(family(members, 120, 3), "doc_id long, text string").repartition(3)
        got = {r.component_id for r in ngram_join.join_components(docs, 5, 90).collect()}
        assert len(got) > members // 2
        figures.append(dict(seen))
    for name in seen:
        assert figures[1][name] <= 3 * figures[0][name] + 50, (name, figures)


def test_all_links_come_through_the_tree(spark, monkeypatch):
    """With a search that returns nothing, only equal sets are joined."""
    rows = family(40, 120, 1)
    assert len({c for *_, c in joined(spark, rows, 5, 80)}) == 1
    monkeypatch.setattr(ngram_join, "tile_hits", lambda *a, **k: iter(()))
    assert len({c for *_, c in joined(spark, rows, 5, 80)}) == 40


def test_hot_tiles_are_dealt_into_chunks(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "UNIT", 8)
    monkeypatch.setattr(ngram_join, "LOCAL", 2)
    monkeypatch.setattr(ngram_join, "GROUP_SHINGLES", 1000)
    for edits in (1, 4):
        rows = family(90, 120, edits)
        assert joined(spark, rows, 5, 80) == brute(rows, 5, 80)


@pytest.mark.parametrize("fanout", [2, 16, 1000])
def test_first_hits_find_one_where_there_is_any(fanout, monkeypatch):
    monkeypatch.setattr(ngram_join, "FANOUT", fanout)
    _, sizes, points = sized_points(5, 120, 20, 60)
    starts = np.array([0, 2, 30, 33])
    nodes = np.arange(120)
    every = {}
    for i, j in ngram_join.tile_hits(points, sizes, nodes, starts, 80):
        for a, b in zip(i.tolist(), j.tolist()):
            every.setdefault(max(a, b), set()).add(min(a, b))
    first = [(a, b) for i, j in ngram_join.tile_hits(points, sizes, nodes, starts, 80, first_only=True) for a, b in zip(i.tolist(), j.tolist())]
    assert dict(first) == {a: min(b) for a, b in every.items()} and len(first) == len(every)


def test_spanning_links_join_what_links():
    rng = np.random.default_rng(7)
    for percent in (50, 80):
        sets = [np.unique(rng.integers(0, 30, rng.integers(1, 20), dtype=np.uint64)) for _ in range(40)]
        parent = list(range(40))

        def root(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for i in range(40):
            for j in range(i):
                if 100 * len(np.intersect1d(sets[i], sets[j])) >= percent * len(np.union1d(sets[i], sets[j])):
                    parent[root(i)] = root(j)
        label = list(range(40))
        for i, j in ngram_join.spanning_links(sets, np.arange(40), percent):
            assert 100 * len(np.intersect1d(sets[i], sets[j])) >= percent * len(np.union1d(sets[i], sets[j]))
            a, b = label[i], label[j]
            label = [a if x == b else x for x in label]
        assert all((label[i] == label[j]) == (root(i) == root(j)) for i in range(40) for j in range(40))
