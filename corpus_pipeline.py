"""The corpus pipeline: five stages over ``documents``, each by one training-data operator.

A stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as
Parquet to the shared folder and read again as the next stage's docs. All but
the last return the columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweld.llm import mixing, quality_bayes, simhash_bk, suffix_dedup, token_packing
from graphweld.llm.common import delete_folder, shared_folder

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier doesn't reject."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality_bayes.keep_good(docs.select(*COLUMNS), labels)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: shingles of five words, similarity of 0.8 and more."""
    return simhash_bk.one_of_each(docs.select(*COLUMNS))


def suffix_strip(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents without the byte strings that stand anywhere else too."""
    rest = suffix_dedup.strip(docs, with_text=True, keep=("lang", "source"))
    return rest.select("doc_id", "text", "lang", "source", F.length("text").cast("long").alias("n_chars"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of the mixture, repeated as often as it takes them."""
    return mixing.mixed_documents(docs.select(*COLUMNS))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with their sequences."""
    return token_packing.pack(docs)


STAGES = [("quality_classifier", quality), ("simhash_near_dedup", near_dedup), ("suffix_array_dedup", suffix_strip), ("mix_sources", mix_sources), ("best_fit_packing", pack)]
#: SQL can't express the stages; tests/llm/test_operators.py holds their operators against plain versions or invariants, test_pipeline.py only the counts and columns of the chain.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; the last one's rows. A stage's folder is deleted when the next one is written; the last one's input stays, as the result reads it."""
    home = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{home}/{name}")
        docs = spark.read.parquet(f"{home}/{name}")
        if before:
            delete_folder(spark, before)
        before = f"{home}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
