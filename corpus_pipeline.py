"""Corpus pipeline: toxicity, near duplicates, benchmark decontamination, source mixing, token files.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, written as Parquet and read again as
the next stage's docs. All but the last return the columns of documents. What a finished stage wrote
besides its result is deleted, and its result once the next stage's is there.

Defined cases, in every stage: a null text counts as an empty one, which is neither toxic by a hit nor
like any other, holds no benchmark item, takes no words in the mix and so ends there; a null doc_id is
kept and never a copy of another row; rows that repeat a doc_id are one document for the near-duplicate
stage and rows of their own before it; ties go to the smaller doc_id; other columns than those of
documents are carried along; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spreadlab.llm.decontaminate import drop_leaks
from spreadlab.llm.jaccard import keep_one_each
from spreadlab.llm.mixing import mix_documents
from spreadlab.llm.token_frames import token_digest
from spreadlab.llm.toxicity import drop_toxic, fit_for
from spreadlab.storage import discard, materialize, scratch_scope


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon model scores below 0.3."""
    return drop_toxic(docs, fit_for(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")), 0.3)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by 5-word shingles at a Jaccard similarity of 0.8."""
    return keep_one_each(docs, k=5, num=80, den=100)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no copy of a benchmark item."""
    return drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target weights; repeats are rows of their own."""
    return mix_documents(docs)


def token_files(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files written and read back: one row per document of the mix."""
    return token_digest(docs)


STAGES = [
    ("toxicity", reject_toxic),
    ("near_duplicates", one_of_each_group),
    ("decontamination", without_benchmark),
    ("mixing", mixed_sources),
    ("token_files", token_files),
]

# Learnt weights, alignment and file formats are beyond SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        with scratch_scope(spark) as made:
            kept = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
            made.remove(kept._scratch)
        discard(docs)
        docs = kept
    return STAGES[-1][1](spark, docs, sf_dir)
