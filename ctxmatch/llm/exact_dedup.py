"""Exact deduplication by a tree-merge of sorted digest runs.

Every input partition sorts its digests into a run in which equal digests are already combined. The runs then meet in
rounds: the partitions ("lanes") are numbered in base ``fan_in``, and in round r each lane trades with the lanes that
differ from it in digit r only, giving each of them the digests whose r-th digit is theirs (binomial rounds with a fan-in of 2; more lanes meet at once by default). What a lane
receives is merged multiway and combined again, so after the last round each lane owns a range of digests, fully merged. The engine's exchange keeps no order of its senders, so its
sort, which spills, stands in for a heap over the received runs. A group of copies, however large, shrinks to at most one entry per lane before it travels, and no task ever sees
more than one entry per sender for it. Documents then find their group by a join on the digest, whose hot keys the engine's adaptive execution splits.

An entry is (digest, bytes, second hash, smallest id, count). Entries are combined only when the SHA-256 digest, the
length and an independent 64-bit hash all agree, so the smallest id is verified at every level.

Defined cases: null text counts as empty; empty texts form one group; white space (space, tab to carriage return) runs
compare as one space; rows with a null id are returned with the smallest id of their group (null if it has none) and are
never the row that stays unless the whole group has null ids; a row given twice with the same id is returned twice; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of

SPACE = r"[\x20\x09-\x0D]+"
_KEY = ["digest", "n_bytes", "check"]


def normalised(col: Column) -> Column:
    return F.regexp_replace(col, SPACE, " ")


def merge_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Combine equal neighbours of a sorted stream; holds one batch and the entry that may continue in the next."""
    open_entry: pa.Table | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = pa.Table.from_batches([batch])
        if open_entry is not None:
            rows = pa.concat_tables([open_entry, rows])
        done = (
            rows.group_by([*_KEY, "lane"], use_threads=False)
            .aggregate([("keep_id", "min"), ("n_rows", "sum")])
            .rename_columns([*_KEY, "lane", "keep_id", "n_rows"])
            .select(rows.column_names)
            .cast(rows.schema)
        )
        open_entry = done.slice(done.num_rows - 1)
        yield from done.slice(0, done.num_rows - 1).to_batches()
    if open_entry is not None:
        yield from open_entry.to_batches()


def _merged(df: DataFrame) -> DataFrame:
    return df.sortWithinPartitions(*_KEY).mapInArrow(merge_runs, df.schema)


def lanes_for(partitions: int, most_fan_in: int = 32) -> tuple[int, int]:
    """(fan-in, rounds) with fan_in ** rounds lanes, at least as many as ``partitions``."""
    rounds = max(1, 2 if partitions > 4 else 1, math.ceil(math.log(max(partitions, 2), most_fan_in)))
    fan_in = max(2, math.ceil(partitions ** (1 / rounds) - 1e-9))
    return fan_in, rounds


def digest_groups(docs: DataFrame, *, fan_in: int | None = None, rounds: int | None = None) -> DataFrame:
    """One row per distinct normalised text: digest, n_bytes, check, keep_id, n_rows."""
    if fan_in is None or rounds is None:
        fan_in, rounds = lanes_for(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    lanes = fan_in**rounds
    digit = F.conv(F.substring(F.hex("digest"), 1, 8), 16, 10).cast("long") % F.lit(lanes)
    runs = docs.select(*_KEY, F.col("doc_id").cast("long").alias("keep_id"), F.lit(1).cast("long").alias("n_rows"), (F.spark_partition_id() % lanes).cast("int").alias("lane"))
    runs = _merged(runs)
    for r in range(rounds):
        unit = fan_in**r
        own = F.floor(F.col("lane") / (unit * fan_in)) * (unit * fan_in) + F.col("lane") % unit
        runs = runs.withColumn("lane", (own + F.floor(digit / unit) % fan_in * unit).cast("int"))
        runs = _merged(runs.repartitionById(lanes, F.col("lane")))
    return runs.drop("lane")


def mark_copies(docs: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    text = normalised(text_of())
    hashed = docs.select("doc_id", F.unhex(F.sha2(text, 256)).alias("digest"), F.octet_length(text).cast("long").alias("n_bytes"), F.xxhash64(text).alias("check"))
    groups = digest_groups(hashed, **options)
    return hashed.join(groups, _KEY).select(
        "doc_id", "keep_id", F.col("n_rows").alias("group_size"), F.col("doc_id").cast("long").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256")
    )


def drop_copies(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with only the row of smallest id of each group of equal texts."""
    stay = mark_copies(docs, **options).filter("kept").select(F.col("doc_id").alias("_stay_id")).distinct()
    return docs.join(stay, docs["doc_id"].eqNullSafe(stay["_stay_id"]), "left_semi").select(*docs.columns)


ORACLE = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents),
     g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, CAST(g.group_size AS BIGINT) AS group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256
FROM n JOIN g USING (t)
"""
