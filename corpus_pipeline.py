"""Corpus pipeline: quality, near duplicates, benchmark decontamination, mixing, sharding.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame. ``run`` writes each
stage's rows as Parquet under the shared checkpoint folder and reads them again as the next one's documents.

Every stage takes nulls in any column, empty and very long texts, repeated rows, empty tables and further columns, whatever their
names, which it keeps (the last one returns its own); what it makes of them is said at each.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from placeminer.llm import hashtree, jaccard, langid, mixing, quality, tiling
from placeminer.llm.common import checkpoint_dir, table

ORACLE_SQL = None


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts; it learns from labels as query op5 does.

    Null and empty texts have the score of an empty document; repeated rows stay or go together; without labels all stay.
    """
    labels = table(spark, sf_dir, "labels").where(~langid.held_out(3, 1))
    return quality.filtered(docs, quality.fit(docs.where(~langid.held_out(3, 1)), labels))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one with the least doc_id.

    Texts without a word have no duplicate and stay, and so do rows without a doc_id; of rows that repeat a doc_id one stays.
    """
    return jaccard.representatives(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item.

    Null and empty texts hold none; items of fewer than five words are held by none; repeated rows stay or go together.
    """
    return tiling.clean(docs, table(spark, sf_dir, "benchmark"))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, at most three times.

    Texts without a word are not taken; a null source is one source; rows that repeat a doc_id are one document, rows without one are told apart by source and text.
    """
    return mixing.mixed(docs)


def sharding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shard and slot of every row.

    A null text has size 8; all rows without a doc_id have one shard; repeated rows get slots of their own.
    """
    return hashtree.assign(docs)


STAGES = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("mixing", mixing_stage),
    ("sharding", sharding_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
