"""A corpus pipeline: toxic documents go, copies and near copies go, sources are mixed, texts become token ids.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the next stage's ``docs``.
All but the last keep the columns of ``documents``. The mixing stage keeps every row: its decision is the order, in which files and the rows in them follow the schedule,
and the last stage returns it as each row's ``position``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ctxmatch.llm import bpe, exact_dedup, mixing, near_dup, toxicity
from ctxmatch.llm.common import table, written


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that the weakly supervised classifier, fitted on this input, scores at 0.5 or more."""
    return toxicity.drop_toxic(docs, table(spark, sf_dir, "labels"))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    return exact_dedup.drop_copies(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: five words, similarity 0.8."""
    return near_dup.drop_near_copies(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents in the order of a Pfair schedule whose target weights are the square roots of the sources' sizes."""
    return mixing.mixed_order(docs, mixing.tempered(0.5))


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, with digests of the ids and of what they decode to, and its position in the mix.

    The memo is small: Python workers live on, and what they remember would take the next run's memory.
    """
    import public_tokenizers

    return bpe.encode_documents(mixing.positions(docs), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=True, memo=50_000, carry=("position",))


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("near_dedup", drop_near_copies),
    ("mixing", mix_sources),
    ("bpe", tokenize),
]

#: A fitted classifier and BPE have no SQL; tests/llm compares the pipeline with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
