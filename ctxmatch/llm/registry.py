"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, exact_dedup, mixing, near_dup, quality, secrets, sharding, suffix_dedup, toxicity, warc
from .common import table


def op1_pfair_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its block, release, deadline and slot under tempered target weights."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return mixing.mix(docs, mixing.tempered(0.5)).select("doc_id", "source", "block", "offset", "release", "deadline", "slot", "phase_start")


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.mark_copies(table(spark, sf_dir, "documents"))


def op3_weak_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_documents(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op4_markov_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return secrets.find_secrets(table(spark, sf_dir, "documents"), words=secrets.words_of(public_tokenizers.path("byte_bpe_50k.tiktoken")))


def op5_repeat_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return bpe.encode_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, memo=500_000)


def op7_divergence_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(table(spark, sf_dir, "documents"))


def op8_lpt_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_pages(table(spark, sf_dir, "pages"))


def op10_odd_sketch_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_components(table(spark, sf_dir, "documents"), words=4)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_pfair_mix, op2_exact_dedup, op3_weak_toxicity, op4_markov_secrets, op5_repeat_removal, op6_bpe, op7_divergence_rules, op8_lpt_shards, op9_warc, op10_odd_sketch_minhash)}


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_dedup": exact_dedup.ORACLE, "op5_repeat_removal": suffix_dedup.ORACLE, "op7_divergence_rules": quality.oracle(), "op9_warc": warc.ORACLE, "op10_odd_sketch_minhash": near_dup.ORACLE}
