"""Queries of this subpackage and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, extract, hashtree, jaccard, langid, mixing, quality, rules, surrogates, tiling
from .common import checkpoint_dir, table


def op1_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return surrogates.replaced(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op2_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.fit(docs.where(~langid.held_out(4, 2)))
    keyed = docs.select("doc_id", "text")
    return langid.predict(keyed, model).select("doc_id", langid.held_out(4, 2).alias("held_out"), "lang_pred", "score")


def op3_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.verdicts(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def ledger_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each rule of each policy does, from the stored ledger of op 3."""
    return rules.ablation(rules.stored(table(spark, sf_dir, "documents"), f"{checkpoint_dir(spark)}/ledger-{uuid.uuid4().hex}"))


def op4_hashtree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashtree.assign(table(spark, sf_dir, "documents"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = quality.fit(docs.where(~langid.held_out(3, 1)), labels.where(~langid.held_out(3, 1)))
    scored = quality.scores(docs, model)
    return scored.select("doc_id", langid.held_out(3, 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op6_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.groups(table(spark, sf_dir, "documents"))


def op7_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract.extract(table(spark, sf_dir, "pages"))


def op8_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiling.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.counts(table(spark, sf_dir, "documents"))


def op10_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_surrogates": op1_surrogates,
        "op2_language": op2_language,
        "op3_rules": op3_rules,
        "ledger_ablation": ledger_ablation,
        "op4_hashtree": op4_hashtree,
        "op5_quality": op5_quality,
        "op6_jaccard": op6_jaccard,
        "op7_extraction": op7_extraction,
        "op8_tiling": op8_tiling,
        "op9_tokens": op9_tokens,
        "op10_mixture": op10_mixture,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_rules": rules.oracle(),
        "ledger_ablation": rules.ablation_oracle(),
        "op4_hashtree": hashtree.oracle(),
        "op6_jaccard": jaccard.oracle(),
    }
