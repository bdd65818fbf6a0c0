"""The pipeline's stages against plain versions, on the smallest documents and on hard rows."""

import re

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from edgefold.llm import decontaminate, line_dedup, ngram_join, quality

from .test_ngram_join import brute


def test_stages_work_on_what_the_one_before_kept(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    first = cp.quality_rules(spark, docs, small).cache()
    kept = {r.doc_id for r in quality.judge(docs).where("kept").collect()}
    assert {r.doc_id for r in first.select("doc_id").collect()} == kept and first.columns == columns

    second = cp.dedup_lines(spark, first, small).cache()
    assert second.columns == columns and second.count() == len(kept)
    assert {(r["row"]["doc_id"], r["text"]) for r in line_dedup.dedup_lines(first).collect()} == {(r.doc_id, r.text) for r in second.collect()}
    assert second.where(F.length("text") != F.col("n_chars")).count() == 0

    third = cp.near_duplicates(spark, second, small).cache()
    groups = brute([(r.doc_id, r.text) for r in second.collect()], 5, 80)
    assert {r.doc_id for r in third.collect()} == {g for _, _, g in groups} and third.columns == columns

    fourth = cp.decontamination(spark, third, small).cache()
    items = [r.text for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    assert fourth.columns == columns and not any(i in r.text for r in fourth.collect() for i in items)
    dropped = {r.doc_id for r in third.collect()} - {r.doc_id for r in fourth.collect()}
    assert dropped == {r.doc_id for r in decontaminate.contaminated(third, spark.read.parquet(f"{small}/benchmark.parquet")).collect()}

    packed = cp.pack(spark, fourth, small)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == {r.doc_id for r in fourth.collect()}


def test_repeated_rows_and_nulls(spark, small):
    words = " ".join(f"w{i}" for i in range(60))
    rows = [(1, words), (1, words), (2, words + " x"), (None, words), (3, None), (4, ""), (5, "other " * 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in cp.near_duplicates(spark, docs, small).collect()), key=repr)
    assert got == sorted([(1, words), (None, words), (3, None), (4, ""), (5, "other " * 3)], key=repr)


def test_run_gives_rows(spark, small):
    assert cp.run(spark, small).count() > 0 and cp.ORACLE_SQL is None and len(cp.STAGES) == 5


def test_different_texts_under_one_id_are_judged_each(spark, small):
    a, b = (" ".join(f"{p}{i}" for i in range(60)) for p in "ab")
    rows = [(1, b), (2, a), (2, b + " x"), (2, a), (3, a + " y")]
    got = [(r.doc_id, r.text) for r in cp.near_duplicates(spark, spark.createDataFrame(rows, "doc_id long, text string"), small).collect()]
    assert sorted(got) == [(1, b), (2, a)]


def test_contaminated_rows_go_whatever_their_id(spark, small):
    item = spark.read.parquet(f"{small}/benchmark.parquet").where("length(text) > 80").first().text
    rows = [(None, "before " + item + " after", 1), (7, item, 2), (7, "clean text", 3), (None, None, 4), (8, "", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, row long")
    got = cp.decontamination(spark, docs, small)
    assert got.columns == docs.columns and sorted(r.row for r in got.collect()) == [3, 4, 5]
