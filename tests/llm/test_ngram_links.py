"""All links between class representatives, those within a component too."""

import random

from edgefold.llm import ngram_join


def test_links_equal_all_pairs(spark):
    rng, texts = random.Random(1), []
    for _ in range(6):
        base = rng.choices("abcdefghijklmnop", k=60)
        for _ in range(20):
            words = list(base)
            for _ in range(rng.randint(0, 2)):
                words[rng.randrange(60)] = rng.choice("xyz")
            texts.append(" ".join(words))
    sets = {}
    for i, t in enumerate(texts):
        w = t.split()
        sets.setdefault(frozenset(tuple(w[j : j + 3]) for j in range(len(w) - 2)), i)
    want = sorted((min(i, j), max(i, j)) for x, i in sets.items() for y, j in sets.items() if i < j and 100 * len(x & y) >= 80 * len(x | y))
    got = ngram_join.join_links(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), k=3, percent=80).collect()
    assert len(want) > len(texts) and sorted((r.a, r.b) for r in got) == want
