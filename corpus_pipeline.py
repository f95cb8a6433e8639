"""A corpus pipeline of four stages, each written as Parquet and read again: quality, near-duplicates, personal data, packing.

Every stage takes (spark, docs, sf_dir). All but the last return the columns of documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.common import drop_scratch, materialize, ship_package, table
from unscramble.llm.neardup import one_of_each_class
from unscramble.llm.packing import pack_documents
from unscramble.llm.personal import redact
from unscramble.llm.quality import CUT, fit, with_scores


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier doesn't reject. It is fitted to labelled documents among docs."""
    ship_package(spark)
    model = fit(docs, table(spark, sf_dir, "labels"))
    name = "_".join(["score", *docs.columns])  # no column of docs has it
    return with_scores(docs, model, name).filter(F.col(name) >= CUT).drop(name)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates, the one with the smallest doc_id."""
    ship_package(spark)
    return one_of_each_class(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced by its kind."""
    return redact(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document stands in sequences of 4096 tokens."""
    ship_package(spark)
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("packing", packing)]

#: Nearest-neighbour scores, sampling and tokenization have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table documents. What a stage has written goes when the next one has written its own."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        made = materialize(stage(spark, docs, sf_dir), name)
        drop_scratch(docs)
        docs = made
    return STAGES[-1][1](spark, docs, sf_dir)
