"""BM25 search against an exhaustive scorer, and planted items."""

import math
import random
import re
from collections import Counter

import numpy as np

from edgefold.llm import decontaminate as dc

DOC, ITEM = "doc_id long, text string", "item_id long, text string"


def tokens(text):
    return re.findall(r"[^\W_]+", text.lower())


def items_of(seed=1, n=60):
    rng = random.Random(seed)
    vocabulary = [f"t{i}" for i in range(400)] + ["the", "of", "and"] * 30
    return [(i, " ".join(rng.choices(vocabulary, k=rng.randint(12, 60))) + ". " + " ".join(rng.choices(vocabulary, k=rng.randint(1, 9))) + ".") for i in range(n)]


def test_pruned_search_equals_exhaustive_scores():
    """Every passage's items at or above the limit are found with the score of the plain formula."""
    items = items_of()
    index = dc.Index([(i, *dc.parts(t)) for i, t in items])
    bags = [tokens(t) for _, t in items]
    df, mean, n = Counter(w for b in bags for w in set(b)), sum(map(len, bags)) / len(bags), len(bags)

    def weight(word, bag):
        tf = bag.count(word)
        return math.log1p((n - df[word] + 0.5) / (df[word] + 0.5)) * tf * (dc.K1 + 1) / (tf + dc.K1 * (1 - dc.B + dc.B * len(bag) / mean))

    own = [sum(weight(w, b) for w in set(b)) for b in bags]
    rng = random.Random(3)
    text = []
    for i in rng.sample(range(n), 20):
        text += rng.choices([f"u{j}" for j in range(50)], k=rng.randint(0, 40)) + bags[i][: rng.randint(len(bags[i]) // 2, len(bags[i]))]
    hashes = dc.word_hashes([" ".join(text)])[0]
    limit = 0.4
    old = dc.QUESTION_SHARE, dc.ANSWER_SHARE
    dc.QUESTION_SHARE = dc.ANSWER_SHARE = -1.0
    try:
        got = {i: s for _, i, s, _, _ in index.search(hashes, np.zeros(len(hashes), dtype=np.int64), 1, limit)}
    finally:
        dc.QUESTION_SHARE, dc.ANSWER_SHARE = old
    want = {}
    for group in index.groups:
        stride = group.length // 2
        for a in range(0, max(1, len(text)), stride):
            passage = set(text[a : a + group.length])
            for i in group.members:
                score = sum(weight(w, bags[i]) for w in passage if w in bags[i]) / own[i]
                if score >= limit:
                    want[int(i)] = max(want.get(int(i), 0), score)
    assert set(got) == set(want) and all(abs(got[i] - want[i]) < 1e-3 for i in got)


def test_planted_items_are_found_and_clean_texts_are_not(spark):
    items = items_of(2)
    rng = random.Random(9)
    noise = lambda k: " ".join(rng.choices([t for _, x in items for t in x.split()], k=k))
    docs, want = [], set()
    for d in range(120):
        text = noise(rng.randint(0, 400))
        if d % 3 == 0:
            i, item = items[rng.randrange(len(items))]
            text = text + "\n" + (item.upper() if d % 2 else item.replace(" ", "  ")) + " " + noise(rng.randint(0, 90))
            want.add((d, i))
        docs.append((d, text))
    found = dc.contaminated(spark.createDataFrame(docs, DOC), spark.createDataFrame(items, ITEM)).collect()
    assert {(r.doc_id, r.item_id) for r in found} == want


def test_given_tables_hold_exact_passages(spark, middle):
    docs, items = (spark.read.parquet(f"{middle}/{t}.parquet") for t in ("documents", "benchmark"))
    got = {(r.doc_id, r.item_id) for r in dc.contaminated(docs, items).collect()}
    texts, asked = docs.select("doc_id", "text").collect(), items.collect()
    plain = {(d.doc_id, i.item_id) for d in texts for i in asked if i.text in d.text}
    assert plain <= got
    grams = lambda t: {tuple(w[k : k + 3]) for w in [tokens(t)] for k in range(max(1, len(w) - 2))}
    of = {i.item_id: grams(i.text) for i in asked}
    near = {d.doc_id: grams(d.text) for d in texts}
    assert all(len(of[i] & near[d]) >= 0.5 * len(of[i]) for d, i in got)


def test_question_and_answer_columns(spark):
    items = spark.createDataFrame([(1, "alpha beta gamma delta epsilon zeta", "eta theta iota"), (2, None, None)], "item_id long, q string, a string")
    docs = spark.createDataFrame([(1, "x alpha beta gamma delta epsilon zeta y z eta theta iota"), (2, "alpha beta gamma delta epsilon zeta and no more of it")], DOC)
    found = dc.contaminated(docs, items, question_col="q", answer_col="a").collect()
    assert [(r.doc_id, r.item_id) for r in found] == [(1, 1)]


def test_hard_cases(spark):
    items = spark.createDataFrame([(1, None), (2, ""), (3, "..."), (None, "one two three four five six seven"), (4, "one two three four five six seven"), (4, "one two three four five six seven")], ITEM)
    docs = spark.createDataFrame([(1, None), (None, "one two three four five six seven"), (2, ""), (3, "one two three four five six seven"), (3, "one two three four five six seven")], DOC)
    got = sorted(map(tuple, dc.contaminated(docs, items).select("doc_id", "item_id").collect()), key=repr)
    assert got == sorted([(d, i) for d in (None, 3, 3) for i in (None, 4, 4)], key=repr)
    none = spark.createDataFrame([], ITEM)
    assert dc.contaminated(docs, none).count() == 0 and dc.contaminated(spark.createDataFrame([], DOC), items).count() == 0
