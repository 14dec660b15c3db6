"""Sharding by longest-processing-time scheduling.

Groups of documents that must stay together (equal texts) are sorted by size, and each goes to the shard with the least load so far, found through a heap.
Groups of one size are interchangeable, so the schedule needs the number of groups of each size only: one task streams these counts, largest size first,
holding one number for each shard, and writes how many groups of a size each shard gets. Many groups of one size are dealt in whole
rounds at once, with the loads that one by one would give. Groups are then numbered within their size, and the number tells the shard. The loads are
those of plain LPT over all groups at any size of the corpus, and nothing but the distinct sizes (fewer than the square root of twice the
bytes) meets in one task.

Law: ``bytes`` (sizes near equal). Defined cases: a null text has size 1 and stays with empty texts; a group larger than a fair
share has a shard that is larger by that much; ties of size go by shard number; rows that repeat an id, and rows with a null id, are placed like any others;
very long texts are measured whole; an empty table gives no rows; other columns are ignored; slots order a shard by a hash of the id.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import drop_written, text_of, written


def schedule(sizes: Iterable[tuple[int, int]], shards: int) -> Iterator[tuple[int, list[int]]]:
    """(size, groups of it for each shard) for (size, number of groups) given largest first: each group goes to the least-loaded shard, ties by number."""
    heap = [(0, s) for s in range(shards)]
    for size, n in sizes:
        given = [0] * shards
        if n > 4 * shards:  # whole rounds: all places below a level that n groups just do not exceed
            low, high = heap[0][0], heap[0][0] + n * size
            below = lambda level: [max(0, -((load - level) // size)) for load, _ in heap]  # noqa: E731, B023
            while low < high:
                level = (low + high + 1) // 2
                low, high = (level, high) if sum(below(level)) <= n else (low, level - 1)
            filled = below(low)
            for (_, s), k in zip(heap, filled, strict=True):
                given[s] = k
            heap = [(load + k * size, s) for (load, s), k in zip(heap, filled, strict=True)]
            heapq.heapify(heap)
            n -= sum(filled)
        for _ in range(n):
            load, s = heap[0]
            given[s] += 1
            heapq.heapreplace(heap, (load + size, s))
        yield size, given


def scheduled(sizes: DataFrame, shards: int) -> DataFrame:
    """bytes, ends: for ``sizes`` (bytes, n), where each shard's share of the groups of that size ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        pairs = (pair for batch in batches for pair in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
        for size, given in schedule(pairs, shards):
            rows.append((size, [sum(given[: s + 1]) for s in range(shards)]))
            if len(rows) == 1000:
                yield packed(rows)
                rows = []
        if rows:
            yield packed(rows)

    packed = lambda rows: pa.RecordBatch.from_arrays([pa.array([b for b, _ in rows], pa.int64()), pa.array([e for _, e in rows], pa.list_(pa.int64()))], ["bytes", "ends"])
    return sizes.select("bytes", "n").repartition(1).sortWithinPartitions(F.desc("bytes")).mapInArrow(run, "bytes long, ends array<long>")


def numbered(df: DataFrame, group: str, key: str, slot: str = "slot", *, few: bool = True) -> DataFrame:
    """Adds ``slot``, 0, 1, ... without gaps in each ``group`` in the order of a hash of ``key``, without bringing a group into one task.

    The hash's range is cut into pieces, in proportion to the group's rows: some three pieces for each shuffle partition over all groups, so a group with a
    third of all rows is dealt to many tasks. A piece starts where the pieces before it end. The numbers do not depend on how many pieces there are.
    With ``few`` a row for each group is broadcast; where groups number with the data, the join is left to the engine, which splits hot keys.
    """
    sizes = df.groupBy(group).agg(F.count("*").alias("_nr_size"))
    total = sizes.agg(F.sum("_nr_size")).first()[0] or 0
    each = max(1, total // (3 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    sizes = F.broadcast(sizes) if few else sizes
    high = F.shiftrightunsigned(F.xxhash64(key), 33)  # 31 bits
    cut = df.join(sizes, group).withColumn("_nr_piece", F.shiftright(high * F.ceil(F.col("_nr_size") / each), 31).cast("long")).drop("_nr_size")
    before = Window.partitionBy(group).orderBy("_nr_piece").rowsBetween(Window.unboundedPreceding, -1)
    starts = cut.groupBy(group, "_nr_piece").agg(F.count("*").alias("_nr_n")).withColumn("_nr_start", F.coalesce(F.sum("_nr_n").over(before), F.lit(0))).drop("_nr_n")
    within = Window.partitionBy(group, "_nr_piece").orderBy(high, F.xxhash64(key), key)
    return cut.withColumn("_nr_row", F.row_number().over(within)).join(starts, [group, "_nr_piece"]).withColumn(slot, (F.col("_nr_start") + F.col("_nr_row") - 1).cast("long")).drop("_nr_piece", "_nr_row", "_nr_start")


def assign_shards(docs: DataFrame, shards: int = 8) -> DataFrame:
    """One row per document: doc_id, size, text_crc32, law, shard, slot, grown_shard. Texts are read once."""
    text = text_of()
    sized = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).cast("long").alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("_group"))
    sized = written(sized, "sizes")
    groups = written(sized.groupBy("_group").agg(F.sum("size").alias("bytes")), "groups")
    plan = written(scheduled(groups.groupBy("bytes").agg(F.count("*").alias("n")), shards), "plan")
    ranked = numbered(groups, "bytes", "_group", "_rank", few=False).join(plan, "bytes")
    where = ranked.select("_group", F.size(F.filter("ends", lambda end: end <= F.col("_rank"))).alias("shard"))
    placed = written(sized.join(where, "_group").select("doc_id", "size", "text_crc32", "shard"), "placed")
    drop_written(sized, groups, plan)
    return numbered(placed, "shard", "doc_id").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
