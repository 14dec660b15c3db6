"""Mixing sources to target weights by Pfair scheduling.

The documents of a source form blocks of ``block`` rows. With weight w, block i (from 0) may not start before slot
floor(i / w) and must have run by slot ceil((i + 1) / w); earliest deadline first then keeps every source within less than one block of
w * t after each of the t slots. Weights are exact: the given numbers as fractions of their sum, never rounded, so the bound holds for any
number of slots and sources.

When a source ends, the others share its weight and a new phase starts; phases are at most as many as sources. The driver
sees one row per source. One task schedules the blocks (not the documents) with a heap that holds one block of each source, and streams their slots into a
table, which the documents join by source and block: earliest deadline first is sequential, so ``block`` should grow where a corpus has billions of
documents (some 200,000 blocks a second). Documents are numbered within a source by pieces of a hash's range, so a source with a third of all rows is
numbered by many tasks.

Defined cases: null sources are a source of their own; weights given for missing sources are ignored, sources without a weight (or with 0) come last;
null ids and repeated rows (the same id twice) are mixed like any others, in no set order among themselves; texts are carried along whole, however long;
columns of the input that are named like one of the schedule's come back as ``own_...``; an empty table gives no rows; every row is kept.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Iterator
from fractions import Fraction
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import parts_for, written
from .sharding import numbered

GROUP = 256  # blocks of a source in one row of the schedule's table
TIMES = ("slot", "release", "deadline", "phase_start")
LAST = (1 << 63) - 1  # the largest slot a column holds; only deadlines of nearly weightless sources reach it


def whole_weights(weights: dict[str, float], frame: int) -> dict[str, int]:
    """Largest remainders: whole numbers, at least 1 each, that sum to ``frame`` (or to the number of sources if that is more)."""
    frame = max(frame, len(weights))
    total = sum(weights.values())
    exact = {s: w / total * frame for s, w in weights.items()}
    out = {s: max(1, int(x)) for s, x in exact.items()}
    order = sorted(exact, key=lambda s: (-(exact[s] - int(exact[s])), s))
    while (gap := frame - sum(out.values())) > 0:
        for s in order[:gap]:
            out[s] += 1
    while sum(out.values()) > frame:
        most = max(out, key=lambda s: (out[s], s))
        out[most] -= 1
    return out


def exact_weights(weights: dict[str, float]) -> dict[str, int]:
    """Whole numbers in exactly the ratio of ``weights``."""
    exact = {s: Fraction(w) for s, w in weights.items()}
    unit = math.lcm(*(x.denominator for x in exact.values()))
    return {s: int(x * unit) for s, x in exact.items()}


def earliest_deadlines(shares: dict[str, int]) -> Iterator[tuple[int, str, int, int, int]]:
    """Rows (slot, source, block, release, deadline) without end: earliest deadline first among the released blocks, ties by name."""
    total, slot = sum(shares.values()), 0
    waiting = [(0, s, 0) for s in shares]
    heapq.heapify(waiting)
    ready: list[tuple[int, str, int, int]] = []
    while True:
        while waiting and waiting[0][0] <= slot:
            release, s, i = heapq.heappop(waiting)
            heapq.heappush(ready, (-(-(i + 1) * total // shares[s]), s, i, release))
        due, s, i, release = heapq.heappop(ready)
        assert due > slot, "a deadline was missed"
        yield slot, s, i, release, due
        heapq.heappush(waiting, ((i + 1) * total // shares[s], s, i + 1))
        slot += 1


def frame_schedule(shares: dict[str, int]) -> dict[str, list[int]]:
    """The slots of each source in one frame of as many slots as there are shares."""
    slots: dict[str, list[int]] = {s: [] for s in shares}
    for slot, s, *_ in islice(earliest_deadlines(shares), sum(shares.values())):
        slots[s].append(slot)
    return slots


def schedule(blocks: dict[str, int], weights: dict[str, float], frame: int | None = None) -> Iterator[tuple[str, int, int, int, int, int]]:
    """Rows (source, block, slot, release, deadline, phase's first slot) in order of slots; release and deadline count from that first slot."""
    left, start = dict(blocks), 0
    shares = {s: w for s, w in weights.items() if s in left and w > 0}
    shares = shares if frame else exact_weights(shares)
    while any(left.values()):
        live = {s: n for s, n in shares.items() if left[s]} or {s: 1 for s in left if left[s]}
        done = {s: blocks[s] - left[s] for s in live}
        for slot, s, i, release, due in earliest_deadlines(whole_weights(live, frame) if frame else live):
            yield s, done[s] + i, start + slot, release, due, start
            left[s] -= 1
            if not left[s]:  # the first source runs out
                break
        start += slot + 1


def schedule_table(spark: SparkSession, blocks: dict[str, int], weights: dict[str, float], frame: int | None) -> DataFrame:
    """The schedule with one row for each ``GROUP`` blocks of a source: arrays of slots, releases, deadlines and phases' first slots."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _ in batches:
            pass
        some: dict[str, list[tuple[int, int, int, int]]] = {}
        full: list[tuple] = []
        packed = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)
        for s, i, slot, release, due, start in schedule(blocks, weights, frame):
            group = some.setdefault(s, [])
            group.append((slot, min(release, LAST), min(due, LAST), start))
            if len(group) == GROUP or i + 1 == blocks[s]:
                full.append((s, i // GROUP, *map(list, zip(*some.pop(s), strict=True))))
            if len(full) == 64:
                yield packed(full)
                full = []
        if full:
            yield packed(full)

    names = ["_mix_source", "_mix_group", *(f"_mix_{c}" for c in TIMES)]
    types = [pa.string(), pa.int64()] + [pa.list_(pa.int64())] * len(TIMES)
    table = spark.range(0, 1, 1, 1).mapInArrow(run, "_mix_source string, _mix_group long, " + ", ".join(f"_mix_{c} array<long>" for c in TIMES))
    return written(table, "schedule")


def tempered(power: float) -> Callable[[dict[str, int]], dict[str, float]]:
    """Target weights from the sources' own sizes: share ** power, which lifts small sources for powers under 1."""
    return lambda sizes: {s: n**power for s, n in sizes.items()}


def mix(docs: DataFrame, weights: dict[str, float] | Callable[[dict[str, int]], dict[str, float]], *, block: int = 16, frame: int | None = None) -> DataFrame:
    """``docs`` with block, offset (place in the block), slot, release, deadline and phase_start: slot - phase_start lies in [release, deadline).

    With ``frame`` the weights are first rounded to whole numbers of slots in a frame of that length.
    """
    docs = _set_aside(docs).withColumn("_mix_source", F.coalesce(F.col("source").cast("string"), F.lit("\0null")))
    sizes = {r["_mix_source"]: r["count"] for r in docs.groupBy("_mix_source").count().collect()}  # one row per source
    chosen = weights(sizes) if callable(weights) else {("\0null" if s is None else s): w for s, w in weights.items()}
    table = schedule_table(docs.sparkSession, {s: -(-n // block) for s, n in sizes.items()}, chosen, frame)
    rows = numbered(docs, "_mix_source", "doc_id", "_mix_rank").withColumns({"block": F.floor(F.col("_mix_rank") / block), "offset": (F.col("_mix_rank") % block).cast("int")})
    rows = rows.withColumn("_mix_group", F.floor(F.col("block") / GROUP)).join(table, ["_mix_source", "_mix_group"])
    place = (F.col("block") % GROUP).cast("int")
    return rows.withColumns({c: F.get(f"_mix_{c}", place) for c in TIMES}).drop("_mix_source", "_mix_rank", "_mix_group", *(f"_mix_{c}" for c in TIMES))


def _set_aside(docs: DataFrame) -> DataFrame:
    return docs.withColumnsRenamed({c: f"own_{c}" for c in docs.columns if c in ("block", "offset", *TIMES)})


def mixed_order(docs: DataFrame, weights, **options) -> DataFrame:
    """All rows of ``docs`` with their own columns, in the order of the mix: file after file, row after row."""
    order, kept = ["slot", "offset"], _set_aside(docs).columns
    mixed = mix(docs, weights, **options).repartitionByRange(parts_for(docs, 16 << 20), *order).sortWithinPartitions(*order)
    return mixed.select(*[F.col(c).alias(own) for c, own in zip(kept, docs.columns, strict=True)])


def positions(docs: DataFrame) -> DataFrame:
    """Rows of :func:`mixed_order` that were written to files and read again, with position: 0, 1, ... in the order of the mix.

    Readers deal files to tasks by size, so the order is told from the number of the file and of the row in it. One row per file is broadcast.
    """
    number = lambda pattern: F.regexp_extract("_metadata.file_name", pattern, 1).try_cast("long")
    named = docs.select("*", F.struct(number(r"^part-(\d+)").alias("part"), number(r"[-.]c(\d+)\.").alias("cut"), F.col("_metadata.file_path").alias("path")).alias("_file"), F.col("_metadata.row_index").alias("_row"))
    before = Window.orderBy("_file").rowsBetween(Window.unboundedPreceding, -1)
    starts = named.groupBy("_file").count().select("_file", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_start"))
    # files without numbers have nulls in their key
    return named.join(F.broadcast(starts.withColumnRenamed("_file", "_f")), F.col("_file").eqNullSafe(F.col("_f"))).withColumn("position", F.col("_start") + F.col("_row")).drop("_file", "_f", "_row", "_start")
