"""Every operator on rows with more columns than it needs, some named as its own working columns."""

from pyspark.sql import functions as F

import corpus_pipeline as cp
from edgefold.llm import chat, decontaminate, line_dedup, ngram_join, packing, pii, quality, secrets, token_counts, url_filter
from edgefold.llm.queries import vocabulary

NAMES = "id row key node n s1 s2 point keys task before place ids lines host path rule label score ch _id _t _text _row _v _words _lines a b ta tb component size hub text2 _turn _turns _conv segments".split()


def widened(df):
    return df.select("*", *(F.lit(i).alias(c) for i, c in enumerate(NAMES) if c not in df.columns))


def test_clashing_columns(spark):
    plain = spark.createDataFrame([(1, "one two three four five six " * 6, "s"), (2, "one two three four five six " * 6, "s"), (3, None, None)], "doc_id long, text string, source string")
    docs = widened(plain)
    items = widened(spark.createDataFrame([(7, "one two three four five six")], "item_id long, text string"))
    pages = widened(spark.createDataFrame([(1, "http://a.com/x"), (2, "http://b.org/y")], "page_id long, url string"))
    turns = widened(spark.createDataFrame([(1, 0, "user", "x"), (1, 1, "assistant", "y")], "conv_id long, turn long, role string, text string"))
    byte, word = vocabulary("byte_bpe_50k.json"), vocabulary("word_bpe_49k.json")
    pairs = (
        (lambda d: chat.digest(chat.format_chats(d)), turns, 1), (ngram_join.join_components, docs, 3), (quality.judge, docs, 3), (lambda d: decontaminate.contaminated(d, items), docs, 2),
        (lambda d: secrets.digest(secrets.find_secrets(d)), docs, 3), (lambda d: packing.pack(d, byte), docs, 3), (url_filter.judge_urls, pages, 2), (line_dedup.dedup_lines, docs, 3),
        (lambda d: token_counts.count_tokens(d, word), docs, 3), (pii.pseudonymise, docs, 3),
    )
    for operator, rows, n in pairs:
        assert operator(rows).count() == n
    for stage in (cp.dedup_lines, cp.near_duplicates):
        assert stage(spark, docs, "").columns == docs.columns
    assert quality.keep(docs).columns == docs.columns
