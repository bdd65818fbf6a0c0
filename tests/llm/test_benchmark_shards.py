"""Scores do not depend on how the benchmark is dealt into shards."""

import random

from edgefold.llm import decontaminate


def test_shards_score_as_one_index(spark, monkeypatch):
    rng = random.Random(1)
    items = [(i, " ".join(rng.choices([f"w{j}" for j in range(60)], weights=range(1, 61), k=rng.randint(8, 20))) + ". " + " ".join(rng.choices([f"w{j}" for j in range(60)], k=4))) for i in range(9)]
    texts = [(i, " ".join(t.split()[: len(t.split()) - rng.randint(0, 3)])) for i, t in items]
    docs, bench = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    search = lambda: sorted(map(tuple, decontaminate.contaminated(docs, bench, limit=0.3).collect()))
    whole = search()
    monkeypatch.setattr(decontaminate, "SHARD", 4)
    assert whole and search() == whole


def test_many_shards_take_one_pass(spark, monkeypatch):
    """2,000 items in shards of 64 give the hits of one index, from a single scan; a long item bounds its own windows."""
    import random

    from edgefold.llm import decontaminate

    rng = random.Random(3)
    vocabulary = [f"v{i}" for i in range(4000)]
    items = [(i, " ".join(rng.choices(vocabulary, k=rng.randint(8, 40))) + ". " + " ".join(rng.choices(vocabulary, k=4))) for i in range(2000)]
    items[0] = (0, " ".join(rng.choices(vocabulary, k=20_000)))
    texts = []
    for n in range(300):
        words = rng.choices(vocabulary, k=rng.randint(50, 400))
        if n % 3 == 0:
            words[20:20] = items[rng.randrange(1, 2000)][1].split()
        texts.append((n, " ".join(words)))
    docs, bench = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    rows = lambda df: sorted(map(tuple, df.collect()))
    whole = decontaminate.contaminated(docs, bench)
    want = rows(whole)
    monkeypatch.setattr(decontaminate, "SHARD", 64)
    split = decontaminate.contaminated(docs, bench)
    # Words of other items weigh the same in every shard; shares are held as 32-bit floats.
    assert [r[:2] for r in rows(split)] == [r[:2] for r in want] and len({r[0] for r in want}) >= 100
    plan = split._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1 and "Union" not in plan
