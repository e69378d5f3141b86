"""From raw documents to packed training windows: quality rules, classifier, near copies, packing.

Each stage takes the session, the documents kept so far and the folder of the tables.  Its result is
written as Parquet in the shared folder and read again by the next one.

Defined cases: null and empty texts fail the rules and go; texts of any length are judged whole; repeated
rows are copies, of which one stays; rows without an id are never copies of others; an empty table gives
an empty result; other columns are carried up to the packing, whose result has its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from outline_engine.llm import classifier, packing, quality_rules, simhash
from outline_engine.llm.storage import materialise, table


def stage_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules reject go."""
    return quality_rules.keep_good(docs)


def stage_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go.  It learns from the labelled rows of the raw table, where bad ones still are."""
    features = classifier.with_statistics(table(spark, sf_dir, "documents"))
    return classifier.keep_predicted(docs, classifier.learn(features, table(spark, sf_dir, "labels")))


def stage_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies, met by deletion variants of fingerprints and by bands, the document with the smallest id stays."""
    return simhash.drop_near_copies(docs)


def stage_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per piece of a document in a window."""
    return packing.pack(docs)


STAGES = [
    ("quality rules", stage_rules),
    ("quality classifier", stage_classifier),
    ("simhash near-dedup", stage_near_copies),
    ("packing", stage_packing),
]

#: Hashing by bits and tokenizing are beyond SQL.  Tests hold the near copies against brute force, the pieces of the
#: packing against the tokenizer, and the columns and rows that each stage keeps.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
