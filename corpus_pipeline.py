"""The training-data pipeline: five operators, each working on all that the one before kept.

``run`` applies the stages to ``documents``. A stage is (name, function); a function takes (spark, docs,
sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next stage's docs.
Near duplicates here share 80 % of their five-word shingles.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgefold.llm import decontaminate, line_dedup, ngram_join, packing, quality
from edgefold.llm.queries import table, vocabulary
from edgefold.runtime.scratch import save

#: Most ids that are broadcast to drop their documents.
BROADCAST_IDS = 500_000


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep(docs)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    done = line_dedup.dedup_lines(docs)
    new = {"text": F.col("text"), "n_chars": F.coalesce(F.length("text"), F.lit(0)).cast("long")}
    return done.select(*(new[c].alias(c) if c in new else F.col(f"row.{c}").alias(c) for c in docs.columns))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: that of the smallest id, the first of its rows.

    Rows are numbered, so a document is a row, whatever ids repeat: of equal rows one stays, of different
    texts under one id each is judged for itself. Rows without an id link with nothing, as in the join, and stay.
    """
    numbered = save(docs.select(F.monotonically_increasing_id().alias("number"), F.struct(*docs.columns).alias("doc")), "numbered")
    named = numbered.where("doc.doc_id IS NOT NULL").select("number", "doc.doc_id", "doc.text")
    found = save(ngram_join.join_components(named, id_col="number").select("number", F.col("component_id").alias("component")), "groups")
    ranked = found.join(named.select("number", "doc_id"), "number").groupBy("component").agg(F.min(F.struct("doc_id", "number")).alias("first"), F.count("*").alias("n"))
    dropped = save(found.join(ranked.where("n > 1"), "component").where("number <> first.number").select("number"), "dropped")
    few = F.broadcast(dropped) if dropped.count() <= BROADCAST_IDS else dropped
    return numbered.join(few, "number", "left_anti").select("doc.*")


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("quality rules", quality_rules),
    ("line dedup", dedup_lines),
    ("n-gram Jaccard join", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("packing", pack),
]

#: The join's hashes, BM25 and the tokenizer are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = save(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
