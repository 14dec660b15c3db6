"""Baselines that need no training."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import encode
from ..plans import augment, serialize
from ..sources.catalog import Catalog
from .block import knn, ranked


def table_retrieval(cat: Catalog, *, kind: str = "META", dim: int = 64, options: serialize.Options = serialize.Options(), t: int | None = None) -> DataFrame:
    """SIMDOC: source_schema, column_id, target_schema, table_id, score, rank: the first t tables (all without t) of each other schema by cosine of the column's sentence and the table's document."""
    rac = augment.build(cat, d_max=1, kind=kind, options=options)
    cols = encode.word_vectors(rac.select("schema_id", "column_id", "text"), ["schema_id", "column_id"], "text", dim).withColumnRenamed("column_id", "query")
    docs = encode.word_vectors(serialize.table(cat, options), ["schema_id", "table_id"], "text", dim).withColumnRenamed("table_id", "neighbour")
    found = knn(cols, docs, t, metric="cosine", across="schema_id")
    return found.select(F.split("query", "[.]")[0].alias("source_schema"), F.col("query").alias("column_id"), F.col("schema_id").alias("target_schema"), F.col("neighbour").alias("table_id"), F.col("dist").alias("score"), "rank")


def random_tables(cat: Catalog, seed: int = 0) -> DataFrame:
    """The floor: tables in the order of a hash; expected recall at t is t / tables."""
    rows = cat.columns.select(F.col("schema_id").alias("source_schema"), "column_id").join(cat.tables.select(F.col("schema_id").alias("target_schema"), "table_id"), F.col("source_schema") != F.col("target_schema"))
    rows = rows.withColumn("score", F.md5(F.concat_ws("|", F.lit(str(seed)), "column_id", "target_schema", "table_id")))
    return ranked(rows, ["column_id", "target_schema"], [F.col("score"), F.col("table_id")], None)
