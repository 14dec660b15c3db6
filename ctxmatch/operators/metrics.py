"""Accuracy and cost measures, as plans over ranked results and truth."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def table_truth(truth: DataFrame) -> DataFrame:
    """M': source_schema, column_id, target_schema, table_id from directed column pairs."""
    return truth.select("source_schema", "column_id", "target_schema", F.split("target_column", "[.]")[1].alias("table_id")).distinct()


def _cuts(df: DataFrame, cuts: list[int], name: str) -> DataFrame:
    return df.withColumn(name, F.explode(F.array(*map(F.lit, cuts))))


def recall_at(ranked: DataFrame, truth: DataFrame, cuts: list[int], *, query: str, item: str, by: list[str], cutoff: str, unit: str = "pair") -> DataFrame:
    """by, cutoff, recall: the share of truth found within the cutoff. ``unit='pair'`` counts (query, item) rows; ``'any'`` and ``'all'`` count queries with one or all of their items found."""
    found = truth.join(ranked.select(*by, query, item, "rank"), [*by, query, item], "left")
    rows = _cuts(found, cuts, cutoff).withColumn("hit", F.coalesce(F.col("rank") <= F.col(cutoff), F.lit(False)))
    if unit != "pair":
        rows = rows.groupBy(*by, query, cutoff).agg((F.bool_or("hit") if unit == "any" else F.bool_and("hit")).alias("hit"))
    return rows.groupBy(*by, cutoff).agg(F.round(F.avg(F.col("hit").cast("double")), 6).alias("recall"))


def recall_of_hits(ranked: DataFrame, total: DataFrame, cuts: list[int], *, by: list[str], cutoff: str) -> DataFrame:
    """by, cutoff, recall of results that say themselves whether they are a ``hit``; ``total``: one row with the number of true pairs, which are not listed."""
    counts = ranked.groupBy(*by).agg(*[F.count(F.when(F.col("hit") & (F.col("rank") <= c), 1)).alias(f"_{c}") for c in cuts]).crossJoin(total)
    return counts.select(*by, F.inline(F.array(*[F.struct(F.lit(c).alias(cutoff), F.round(F.col(f"_{c}") / F.col("total"), 6).alias("recall")) for c in cuts])))


def map_at(ranked: DataFrame, truth: DataFrame, cuts: list[int], *, query: str, item: str, by: list[str], cutoff: str = "k", norm: str = "min") -> DataFrame:
    """by, cutoff, map: mean over queries with a true item of average precision within the cutoff, divided by min(relevant, k) or by all relevant."""
    relevant = truth.groupBy(*by, query).agg(F.count("*").alias("relevant"))
    hits = ranked.join(truth.select(*by, query, item), [*by, query, item]).withColumn("hits", F.row_number().over(Window.partitionBy(*by, query).orderBy("rank")))
    per = _cuts(hits, cuts, cutoff).filter(F.col("rank") <= F.col(cutoff)).groupBy(*by, query, cutoff).agg(F.sum(F.col("hits") / F.col("rank")).alias("s"))
    all_queries = _cuts(relevant, cuts, cutoff)
    bottom = F.least(F.col("relevant"), F.col(cutoff)) if norm == "min" else F.col("relevant")
    return all_queries.join(per, [*by, query, cutoff], "left").groupBy(*by, cutoff).agg(F.round(F.avg(F.coalesce("s", F.lit(0.0)) / bottom), 6).alias("map"))


def precision_f1_mrr(ranked: DataFrame, truth: DataFrame, cuts: list[int], *, query: str, item: str, by: list[str], cutoff: str = "k") -> DataFrame:
    """by, cutoff, precision, f1, mrr over queries with a true item."""
    relevant = truth.groupBy(*by, query).agg(F.count("*").alias("relevant"))
    hits = ranked.join(truth.select(*by, query, item), [*by, query, item])
    per = _cuts(hits, cuts, cutoff).filter(F.col("rank") <= F.col(cutoff)).groupBy(*by, query, cutoff).agg(F.count("*").alias("n"), F.min("rank").alias("first"))
    rows = _cuts(relevant, cuts, cutoff).join(per, [*by, query, cutoff], "left")
    n = F.coalesce("n", F.lit(0))
    return rows.groupBy(*by, cutoff).agg(F.round(F.avg(n / F.col(cutoff)), 6).alias("precision"), F.round(F.avg(2 * n / (F.col(cutoff) + F.col("relevant"))), 6).alias("f1"), F.round(F.avg(F.coalesce(1 / F.col("first"), F.lit(0.0))), 6).alias("mrr"))


def over_runs(results: DataFrame, by: list[str]) -> DataFrame:
    """by, mean, std (sample) of ``value`` over runs."""
    return results.groupBy(*by).agg(F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_samp("value"), 6).alias("std"))


def group_means(results: DataFrame, large: str, mean_over: str = "available") -> DataFrame:
    """group, model, t, value: means over scenarios whose target is the large schema, is not, and over all.

    ``available`` averages the scenarios that still have t tables; ``carry_forward`` lets the others keep their last value.
    """
    rows = results.select("scenario", "target", "model", "t", "value")
    if mean_over == "carry_forward":
        span = rows.select("model", "t").distinct().join(rows.select("scenario", "target", "model").distinct(), "model")
        last = Window.partitionBy("scenario", "model").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
        rows = span.join(rows, ["scenario", "target", "model", "t"], "left").withColumn("value", F.last("value", True).over(last)).filter("value is not null")
    part = F.when(F.col("target") == large, "target is large").otherwise("target is not large")
    return rows.withColumn("group", F.explode(F.array(part, F.lit("all")))).groupBy("group", "model", "t").agg(F.round(F.avg("value"), 6).alias("value"))


def gain(a: Column, b: Column) -> Column:
    """Relative gain of a over the baseline b."""
    return F.round((a - b) / b, 6)


def reduction(t: Column, tables: Column) -> Column:
    """Share of the target's tables that need not be searched."""
    return F.round(F.greatest(F.lit(0.0), 1 - t / tables), 6)


def full_recall_t(recalls: DataFrame, by: list[str], cutoff: str = "t") -> DataFrame:
    """The smallest cutoff with full recall; null if there is none."""
    return recalls.groupBy(*by).agg(F.min(F.when(F.col("recall") >= 1, F.col(cutoff))).alias(f"full_{cutoff}"))


def podium(results: DataFrame, by: list[str]) -> DataFrame:
    """Dense rank of models by value."""
    return results.withColumn("place", F.dense_rank().over(Window.partitionBy(*by).orderBy(F.col("value").desc())))


def break_even_t(results: DataFrame, by: list[str]) -> DataFrame:
    """The smallest t from which the constrained value is never below that of the full search (its value at the largest t); ``results``: by, t, value."""
    full = results.groupBy(*by).agg(F.max_by("value", "t").alias("full"))
    below = results.join(full, by).withColumn("bad", F.when(F.col("value") < F.col("full"), F.col("t")))
    return below.groupBy(*by).agg((F.coalesce(F.max("bad"), F.lit(0)) + 1).cast("int").alias("t"))


def kind_effect(values: DataFrame, shares: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Correlation over scenarios between the ``share`` of a kind of matches and ``value``; both keyed by ``scenario``."""
    return values.join(shares, "scenario").groupBy(*by).agg(F.round(F.corr("share", "value"), 6).alias("correlation"))


def only_constrained(results: DataFrame, by: list[str]) -> DataFrame:
    """Rows of ``by`` (which tells k) with full recall at some t though the full search, the value at the largest t, has not; ``t``: the smallest such."""
    rows = results.groupBy(*by).agg(F.max_by("value", "t").alias("full"), F.min(F.when(F.col("value") >= 1, F.col("t"))).alias("t"))
    return rows.filter((F.col("full") < 1) & F.col("t").isNotNull()).drop("full")


def column_reduction(ranked: DataFrame, widths: DataFrame, ts: list[int]) -> DataFrame:
    """target_schema, t, reduction: the share of the target's columns outside the first t tables, mean over the query columns. ``widths``: target_schema, table_id, n_cols."""
    total = widths.groupBy("target_schema").agg(F.sum("n_cols").alias("total"))
    per = _cuts(ranked.join(widths, ["target_schema", "table_id"]), ts, "t").groupBy("column_id", "target_schema", "t").agg(F.sum(F.when(F.col("rank") <= F.col("t"), F.col("n_cols")).otherwise(0)).alias("kept"), F.count("*").alias("tables"))
    return per.filter("t <= tables").join(total, "target_schema").groupBy("target_schema", "t").agg(F.round(F.avg(1 - F.col("kept") / F.col("total")), 6).alias("reduction"))


def sparsity(labels: DataFrame, tables: DataFrame) -> DataFrame:
    """schema_id, positives, cells, share of label cells that are not zero. ``labels``: schema_id, y (map); ``tables``: schema_id, n."""
    rows = labels.groupBy("schema_id").agg(F.sum(F.size("y")).alias("positives"), F.count("*").alias("rows")).join(tables, "schema_id")
    cells = F.col("rows") * F.col("n")
    return rows.select("schema_id", F.col("positives").cast("long").alias("positives"), cells.cast("long").alias("cells"), F.round(F.col("positives") / cells, 6).alias("share"))
