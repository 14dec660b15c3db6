"""Running a streaming plan to the end of what its source holds."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.io import shared_dir


def replay(spark: SparkSession, sf_dir: str, table: str, time: str | None = None, per_trigger: int = 1) -> DataFrame:
    """A file stream of a given table; ``time`` is made a timestamp, which watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return rows.withColumn(time, F.col(time).cast("timestamp")) if time else rows


def finished(stream: DataFrame, mode: str, seen: list | None = None) -> DataFrame:
    """All output of the stream. ``append`` goes to files in the shared folder; ``complete`` and ``update`` results (aggregates) to a table in memory.

    ``seen`` gets the progress of every trigger: rows read, rows dropped as late by the watermark, rows of state.
    """
    spark, tag = stream.sparkSession, uuid.uuid4().hex
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{shared_dir(spark)}/stream-{tag}")
    if mode == "append":
        path = f"{shared_dir(spark)}/stream-out-{tag}"
        running = writer.format("parquet").option("path", path).start()
        running.awaitTermination()
        if seen is not None:
            seen += [{"rows": p.numInputRows, "late": sum(s.numRowsDroppedByWatermark for s in p.stateOperators), "state": sum(s.numRowsTotal for s in p.stateOperators)} for p in running.recentProgress]
        return spark.read.schema(stream.schema).parquet(path)
    writer.format("memory").queryName(f"s{tag}").start().awaitTermination()
    return spark.table(f"s{tag}")


def each_batch(stream: DataFrame, step: Callable[[DataFrame, int], None]) -> None:
    """Every micro-batch through ``step``; a batch that runs again after a failure has the same number, so that steps can be idempotent."""
    tag = uuid.uuid4().hex
    stream.writeStream.foreachBatch(step).trigger(availableNow=True).option("checkpointLocation", f"{shared_dir(stream.sparkSession)}/stream-{tag}").start().awaitTermination()
