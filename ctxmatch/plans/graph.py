"""The table graph of a schema: an edge for each pair of tables that some reference connects."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.catalog import Catalog

MODES = ("directed", "inverse", "undirected")


def edges(cat: Catalog, mode: str = "directed") -> DataFrame:
    """schema_id, src, dst. Directed edges lead from the strong (referenced) table to the weak one, inverse edges back, undirected ones both ways."""
    down = cat.refs.select("schema_id", F.col("strong_table").alias("src"), F.col("weak_table").alias("dst"))
    up = cat.refs.select("schema_id", F.col("weak_table").alias("src"), F.col("strong_table").alias("dst"))
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    return (down if mode == "directed" else up if mode == "inverse" else down.union(up)).distinct()


def neighbours(cat: Catalog) -> DataFrame:
    """schema_id, table_id, weak (tables that refer to it), strong (tables it refers to); sorted, empty where there are none."""
    both = cat.refs.select("schema_id", F.col("strong_table").alias("table_id"), F.col("weak_table").alias("w"), F.lit(None).cast("string").alias("s")).union(
        cat.refs.select("schema_id", F.col("weak_table").alias("table_id"), F.lit(None).cast("string"), F.col("strong_table"))
    )
    found = both.groupBy("schema_id", "table_id").agg(F.array_sort(F.collect_set("w")).alias("weak"), F.array_sort(F.collect_set("s")).alias("strong"))
    none = F.array().cast("array<string>")
    return cat.tables.select("schema_id", "table_id").join(found, ["schema_id", "table_id"], "left").select("schema_id", "table_id", F.coalesce("weak", none).alias("weak"), F.coalesce("strong", none).alias("strong"))
