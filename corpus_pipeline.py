"""A corpus from the given documents: quality, toxicity, near duplicates, mixing, packing.

Each stage takes the documents that the one before kept and returns them with the columns of ``documents``; the last
returns the pieces of the packed sequences. Empty and null texts go with the first stage; an empty table passes through
all stages. ORACLE_SQL is None: SQL can express neither the models nor the tokenizer.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from triplefed.llm import mixing, near_duplicates, packing, quality_rules, toxicity
from triplefed.llm.common import materialize, table

ORACLE_SQL = None


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.good_documents(docs)


def ordinary(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.ordinary_documents(docs, table(spark, sf_dir, "labels"))


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five words, similarity of 0.8 or more."""
    return near_duplicates.first_of_groups(docs, words=5, percent=80)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [("quality_rules", quality), ("toxicity", ordinary), ("near_duplicates", distinct), ("source_mixing", mixed), ("best_fit_packing", packed)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
