"""The thin ``opN_<name>`` queries over the given tables, and their SQL."""

from __future__ import annotations

import functools
import secrets
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, mixing, ngram_join, oracles, pii_surrogates, quality_classifier, quality_rules, secret_automaton, sharding, token_codes, token_counts
from .store import Store

SHARDS = 24


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality_rules.apply_policy(quality_rules.ledger(_docs(spark, sf_dir).select("doc_id", "text")), quality_rules.STANDARD)
    rows = quality_rules.apply_policy(rows.drop("text"), quality_rules.BASE, "base_kept")
    return rows.withColumn("base_failed", ~rows["base_kept"]).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failed")


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(_docs(spark, sf_dir))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.classify(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


@functools.cache
def _drawn_key(application: str) -> bytes:
    return secrets.token_bytes(32)


def surrogate_key(spark: SparkSession) -> bytes:
    """The key that the session names, or else one drawn for this application."""
    named = spark.conf.get("spark.sbgraph.surrogateKey", None)
    return named.encode() if named else _drawn_key(spark.sparkContext.applicationId)


def op4_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_surrogates.rewrite(_docs(spark, sf_dir).select("doc_id", "text"), surrogate_key(spark))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.attribute(_docs(spark, sf_dir))


def op6_secret_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_automaton.report(_docs(spark, sf_dir))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.report(_docs(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(_docs(spark, sf_dir), SHARDS)


def op9_token_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_codes.round_trip(_docs(spark, sf_dir))


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(_docs(spark, sf_dir))


def quality_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Op1's ablation over a stored ledger: texts are read once, policies see bits only."""
    ledger = Store(spark).put("ledger", quality_rules.ledger(_docs(spark, sf_dir).select("doc_id", "text")).drop("text"))
    return quality_rules.ablation(ledger, quality_rules.STANDARD)


def secret_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can express of op6: the base kinds' counts."""
    return secret_automaton.report(_docs(spark, sf_dir)).select("doc_id", "n_assign", "n_access", "n_hex")


def mixing_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What SQL can express of op10: the targets, and the words taken, which come within a hundredth of them."""
    rows = mixing.mix(_docs(spark, sf_dir)).groupBy("source_size", "target").agg(F.sum("taken").alias("taken"))
    return rows.select("source_size", F.round("target", 3).alias("target"), (F.abs(F.col("taken") - F.col("target")) <= 0.01 * F.col("target")).alias("near"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [
        op1_quality_rules,
        op2_ngram_join,
        op3_quality_classifier,
        op4_pii_surrogates,
        op5_token_counts,
        op6_secret_automaton,
        op7_decontamination,
        op8_sharding,
        op9_token_codes,
        op10_mixing,
        quality_ablation,
        secret_base_counts,
        mixing_targets,
    ]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    """The other operators draw from hashes, models or tokenizers; tests compare them with brute force."""
    return dict(oracles.SQL)
