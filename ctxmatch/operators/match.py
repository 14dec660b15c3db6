"""Matching: directions combined, results explained."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def symmetric(ab: DataFrame, ba: DataFrame, how: str = "union") -> DataFrame:
    """column_a, column_b from two directed results (query, target): pairs of either direction, or of both."""
    left = ab.select(F.col("query").alias("column_a"), F.col("target").alias("column_b"))
    right = ba.select(F.col("target").alias("column_a"), F.col("query").alias("column_b"))
    return left.union(right).distinct() if how == "union" else left.intersect(right)


def explain(matches: DataFrame, tables: DataFrame, links: DataFrame | None = None) -> DataFrame:
    """Matches with the suggested tables of their query: an array of (rank, table, p), and whether the match lies in one of them.

    With ``links`` (schema_id, path of shortest undirected paths) also ``link``: how the most probable suggestion leads to the match's table; null without a path.
    """
    ranked_tables = tables.groupBy("query").agg(F.sort_array(F.collect_list(F.struct("rank", "table_id", "p"))).alias("suggested"))
    out = matches.join(ranked_tables, "query", "left")
    out = out.withColumn("within", F.exists("suggested", lambda s: F.split(F.col("target"), "[.]")[1] == s["table_id"]))
    if links is None:
        return out
    ends = links.select(F.col("schema_id").alias("_s"), F.element_at("path", 1).alias("_a"), F.element_at("path", -1).alias("_b"), F.array_join("path", ">").alias("link"))
    at = F.split(F.col("target"), "[.]")
    return out.join(ends, (at[0] == F.col("_s")) & (F.get("suggested", F.lit(0))["table_id"] == F.col("_a")) & (at[1] == F.col("_b")), "left").drop("_s", "_a", "_b")
