"""Files, tables and a catalog data source."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .scenarios import SPECS


def shared_dir(spark) -> str:
    """The folder executors share (``spark.checkpoint.dir``), else one for tests."""
    from ..plans import cut

    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    cut.cut(spark.range(1))
    return spark.sparkContext.getCheckpointDir().rsplit("/", 1)[0]


def round_trip(df: DataFrame, fmt: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write and read in a format, with the explicit schema; partition columns are pruned by filters on them."""
    path = f"{shared_dir(df.sparkSession)}/{fmt}-{uuid.uuid4().hex}"
    writer = df.write.format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
    reader = df.sparkSession.read.format(fmt).schema(df.schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def bucketed(df: DataFrame, name: str, buckets: int, key: str) -> None:
    """A table whose rows lie bucketed and sorted by ``key``: repeated joins and groupings on it shuffle nothing."""
    df.write.bucketBy(buckets, key).sortBy(key).format("parquet").mode("overwrite").saveAsTable(name)


def save_matches(matches: DataFrame, path: str) -> None:
    """Ranked matches, a folder for each pair of schemas."""
    matches.write.mode("overwrite").partitionBy("source_schema", "target_schema").parquet(path)


class CatalogSource(DataSource):
    """``spark.read.format('scenario_catalog')``: columns of a catalog, a partition per table; of the scenario schema named by the option ``schema``, or those given as ``columns`` (JSON rows of ``COLUMNS``)."""

    COLUMNS = ["schema_id", "table_id", "column_name", "ordinal", "dtype", "is_pk"]

    @classmethod
    def name(cls) -> str:
        return "scenario_catalog"

    def schema(self) -> str:
        return "schema_id string, table_id string, column_name string, ordinal int, dtype string, is_pk boolean"

    def reader(self, schema) -> DataSourceReader:
        name = self.options.get("schema", "star")
        given = self.options.get("columns")
        return _CatalogReader([tuple(r) for r in json.loads(given)] if given is not None else [(name, *c[:5]) for c in SPECS[name].columns])


class _CatalogReader(DataSourceReader):
    def __init__(self, rows: list[tuple]):
        self.rows = rows

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(t) for t in dict.fromkeys(r[1] for r in self.rows)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from (r for r in self.rows if r[1] == partition.value)
