"""Augmented columns: every column of every table of every view, with the view's name and neighbours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import labels
from ..sources.catalog import Catalog
from . import graph, paths, serialize


def constraint_text() -> Column:
    """Of ``is_pk`` and ``fk_refs``: primary key, foreign key with what it references, both, or null."""
    foreign = F.array_join(F.transform("fk_refs", lambda r: F.concat(F.lit("foreign key references table "), r["table"], F.lit(" column "), r["column"])), " and ")
    return F.nullif(F.concat_ws(" and ", F.when(F.col("is_pk"), "primary key"), F.nullif(foreign, F.lit(""))), F.lit(""))


def expand(views: DataFrame, cat: Catalog) -> DataFrame:
    """One row per view, table on its path and column of that table."""
    columns = cat.columns.withColumn("constraint", constraint_text()).withColumnRenamed("table_id", "origin_table")
    at = views.select("schema_id", "view_id", "path", F.array_join("path", " ").alias("view_name"), F.posexplode("path").alias("position", "origin_table"))
    return at.join(columns, ["schema_id", "origin_table"])


def context(views: DataFrame, cat: Catalog) -> DataFrame:
    """schema_id, view_id, weak, strong: the neighbours of a view's tables that are not on its path."""
    near = graph.neighbours(cat)
    at = views.select("schema_id", "view_id", "path", F.explode("path").alias("table_id")).join(near, ["schema_id", "table_id"])
    gathered = at.groupBy("schema_id", "view_id", "path").agg(F.flatten(F.collect_list("weak")).alias("w"), F.flatten(F.collect_list("strong")).alias("s"))
    outside = lambda c: F.array_sort(F.array_except(F.array_distinct(c), "path"))
    return gathered.select("schema_id", "view_id", outside("w").alias("weak"), outside("s").alias("strong"))


def build(cat: Catalog, *, mode: str = "directed", d_max: int = 2, decay: float = 0.5, kind: str = "REF", options: serialize.Options | None = None, encoder=None, label: str = "soft") -> DataFrame:
    """Augmented columns with ``text``, labels ``y`` (``soft``, ``onehot`` or ``multihot``) and, given an encoder, the vector ``x``. ``d_max=1``: the original columns."""
    found = paths.views(graph.edges(cat, mode), cat.tables, d_max)
    rows = expand(found, cat).join(context(found, cat), ["schema_id", "view_id"])
    rows = rows.withColumn("text", serialize.column(kind, options or serialize.Options()))
    rows = rows.withColumn("y", labels.soft(F.col("path"), F.col("position"), decay) if label == "soft" else labels.onehot(F.col("path"), F.col("position")) if label == "onehot" else labels.multihot(F.col("path")))
    return encoder.transform(rows, "text", "x") if encoder is not None else rows


def statistics(cat: Catalog, modes: tuple[str, ...] = graph.MODES, d_max: int = 7) -> DataFrame:
    """schema_id, mode, depth, views, columns for every depth from 1 to ``d_max``; all modes are searched together."""
    links, tables = None, None
    for mode in modes:
        e, t = graph.edges(cat, mode).withColumn("mode", F.lit(mode)), cat.tables.withColumn("mode", F.lit(mode))
        links, tables = (e, t) if links is None else (links.union(e), tables.union(t))
    found = paths.views(links, tables, d_max, keys=("schema_id", "mode"))
    widths = cat.tables.select("schema_id", F.col("table_id").alias("t"), "n_cols")
    per = found.select("schema_id", "mode", "view_id", "n_tables", F.explode("path").alias("t")).join(widths, ["schema_id", "t"])
    per = per.groupBy("schema_id", "mode", "n_tables").agg(F.count_distinct("view_id").alias("views"), F.sum("n_cols").alias("columns"))
    depths = tables.select("schema_id", "mode").distinct().withColumn("n_tables", F.explode(F.sequence(F.lit(1), F.lit(d_max))))
    upto = Window.partitionBy("schema_id", "mode").orderBy("n_tables").rowsBetween(Window.unboundedPreceding, 0)
    filled = depths.join(per, ["schema_id", "mode", "n_tables"], "left")
    return filled.select("schema_id", "mode", F.col("n_tables").alias("depth"), F.sum(F.coalesce("views", F.lit(0))).over(upto).alias("views"), F.sum(F.coalesce("columns", F.lit(0))).over(upto).alias("columns"))
