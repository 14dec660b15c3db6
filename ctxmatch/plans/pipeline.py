"""The whole method: predicted tables first, then columns within them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encode import Encoder, HashedNgram
from ..functions.vectors import cosine
from ..models import predict, train
from ..models.mlp import TrainConfig
from ..operators import metrics
from ..operators.block import knn, ranked
from ..sources.catalog import Catalog
from . import augment
from .cut import cut

#: A small network on a narrow encoder: what tests and queries use. The full sizes are the defaults of ``TrainConfig`` and ``HashedNgram``.
QUICK = TrainConfig(hidden=(96, 48), epochs=25, patience=6, folds=3, batch=32, rate=3e-3, decay=1e-4)


def default_t(k: int) -> int:
    """Few tables for few candidates, four or five for many."""
    return 2 if k <= 2 else 3 if k <= 3 else 4 if k <= 10 else 5


def learn(cat: Catalog, kind: str, depth: int, *, config: TrainConfig = QUICK, encoder: Encoder | None = None, table_ser: str = "REF", runs: int = 1, decay: float = 0.5, mode: str = "directed", label: str = "soft") -> DataFrame:
    rac = augment.build(cat, mode=mode, d_max=depth, decay=decay, kind=table_ser, encoder=encoder or HashedNgram(256), label=label)
    return cut(train.train(cut(rac), cat.tables, kind, config=config, runs=runs))


def predict_tables(cat: Catalog, models: DataFrame, kind: str, *, encoder: Encoder | None = None, table_ser: str = "REF", schemas: tuple[str, ...] | None = None) -> DataFrame:
    """run, source_schema, column_id, target_schema, table_id, p, rank for all ordered pairs of schemas."""
    spark = models.sparkSession
    cols = augment.build(cat, d_max=1, kind=table_ser, encoder=encoder or HashedNgram(256)).select("schema_id", "column_id", "x")
    names = schemas or tuple(r[0] for r in cat.tables.select("schema_id").distinct().collect())
    pairs = spark.createDataFrame([(a, b) for a in names for b in names if a != b], "source_schema string, target_schema string")
    return predict.top_tables(predict.scores(cols, models, kind, pairs))


def column_cosines(cat: Catalog, allowed: DataFrame, *, kind: str = "VALS", encoder: Encoder | None = None) -> DataFrame:
    """source_schema, column_id, target_schema, target_column, cosine within the tables of ``allowed`` (column_id, target_schema, table_id, ...), whose other columns stay."""
    rows = augment.build(cat, d_max=1, kind=kind, encoder=encoder or HashedNgram(256)).select("schema_id", "origin_table", "column_id", "x")
    src = rows.select(F.col("schema_id").alias("source_schema"), "column_id", F.col("x").alias("a"))
    tgt = rows.select(F.col("schema_id").alias("target_schema"), F.col("origin_table").alias("table_id"), F.col("column_id").alias("target_column"), F.col("x").alias("b"))
    pairs = src.join(allowed.drop("source_schema"), "column_id").join(tgt, ["target_schema", "table_id"])
    return pairs.withColumn("cosine", F.round(cosine(F.col("a"), F.col("b")), 6) + 0.0).drop("a", "b", "x")


def full_search(cat: Catalog, k: int | None, *, kind: str = "VALS", encoder: Encoder | None = None) -> DataFrame:
    """source_schema, column_id, target_schema, target_column, cosine, rank: the k best columns of every other schema, by blocks of vectors."""
    rows = augment.build(cat, d_max=1, kind=kind, encoder=encoder or HashedNgram(256)).select("schema_id", "column_id", "x")
    found = knn(rows.withColumnRenamed("column_id", "query"), rows.withColumnRenamed("column_id", "neighbour"), k, metric="cosine", across="schema_id")
    return found.select(F.split("query", "[.]")[0].alias("source_schema"), F.col("query").alias("column_id"), F.col("schema_id").alias("target_schema"), F.col("neighbour").alias("target_column"), F.col("dist").alias("cosine"), "rank")


def run(cat: Catalog, *, t: int | None = 4, k: int = 10, kind: str = "HOLO", depth: int = 2, table_ser: str = "REF", column_ser: str = "VALS", **options) -> DataFrame:
    """source_schema, column_id, target_schema, target_column, cosine, rank: the k best columns within the t predicted tables (all tables if t is None)."""
    if t is None:
        return full_search(cat, k, kind=column_ser)
    tables = predict_tables(cat, learn(cat, kind, depth, table_ser=table_ser, **options), kind, table_ser=table_ser)
    allowed = tables.filter((F.col("rank") <= t) & (F.col("run") == 0)).select("column_id", "target_schema", "table_id")
    found = column_cosines(cat, allowed, kind=column_ser)
    return ranked(found.select("source_schema", "column_id", "target_schema", "target_column", "cosine"), ["column_id", "target_schema"], [F.col("cosine").desc(), F.col("target_column")], k)


def table_prediction(cat: Catalog, truth: DataFrame, methods: list[tuple[str, int]], *, runs: int = 1, ts: list[int], **options) -> DataFrame:
    """scenario, target, model, run, t, value: recall at t of each (kind, depth), for every ordered pair of schemas that has truth."""
    out, wanted = None, metrics.table_truth(truth)
    sizes = F.broadcast(cat.tables.groupBy(F.col("schema_id").alias("target_schema")).agg(F.count("*").alias("n")))
    for kind, depth in methods:
        tables = predict_tables(cat, learn(cat, kind, depth, runs=runs, **options), kind)
        every = wanted.withColumn("run", F.explode(F.array(*map(F.lit, range(runs)))))
        rows = metrics.recall_at(tables, every, ts, query="column_id", item="table_id", by=["run", "source_schema", "target_schema"], cutoff="t").join(sizes, "target_schema").filter("t <= n")
        rows = rows.select(F.concat_ws("-", "source_schema", "target_schema").alias("scenario"), F.col("target_schema").alias("target"), F.lit(f"{kind}({depth})").alias("model"), "run", "t", F.col("recall").alias("value"))
        out = rows if out is None else out.union(rows)
    return out


def ablation(cat: Catalog, truth: DataFrame, *, ts: list[int], ks: list[int], kind: str = "HOLO", depth: int = 2, **options) -> DataFrame:
    """source_schema, target_schema, t, k, recall, map of the constrained pipeline; t of all tables is the full search."""
    tables = predict_tables(cat, learn(cat, kind, depth, **options), kind).filter("run = 0").select("column_id", "target_schema", "table_id", F.col("rank").alias("near"))
    found = cut(column_cosines(cat, tables).withColumn("t", F.explode(F.array(*map(F.lit, ts)))).filter("near <= t"))
    found = ranked(found, ["t", "column_id", "target_schema"], [F.col("cosine").desc(), F.col("target_column")], max(ks))
    every = truth.drop("kind").withColumn("t", F.explode(F.array(*map(F.lit, ts))))
    how = {"query": "column_id", "item": "target_column", "by": ["source_schema", "target_schema", "t"]}
    return metrics.recall_at(found, every, ks, cutoff="k", **how).join(metrics.map_at(found, every, ks, **how), ["source_schema", "target_schema", "t", "k"])
