"""Functions for SQL users: ``register(spark)`` makes them callable from statements."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..models import predict
from ..models.mlp import EPS, Mlp
from ..plans import augment, pipeline
from ..plans.cut import cut
from ..sources.catalog import Catalog
from .encode import Encoder, HashedNgram


@F.pandas_udf(T.ArrayType(T.FloatType()))
def encode_text(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    vector = HashedNgram(256).vector
    for texts in batches:
        yield pd.Series([vector(t or "") for t in texts])


@F.pandas_udf(T.DoubleType())
def average_precision(rank: pd.Series, relevant: pd.Series) -> float:
    """Grouped: of the ranked items of one query, over those that are relevant."""
    rows = pd.DataFrame({"rank": rank, "rel": relevant}).sort_values("rank")
    hits = rows["rel"].cumsum()
    found = rows["rel"].sum()
    return float((hits / rows["rank"] * rows["rel"]).sum() / found) if found else 0.0


@F.udtf(returnType="path string, n_tables int")
class ShortestViews:
    """Shortest paths of a small graph given as ``a>b,c>d``: SQL's way to the views of a schema that fits one row."""

    def eval(self, edges: str, d_max: int):
        links: dict[str, list[str]] = {}
        for edge in edges.split(","):
            a, b = edge.split(">")
            links.setdefault(a, []).append(b)
            links.setdefault(b, [])
        for start in sorted(links):
            done, front = {start: [start]}, [[start]]
            yield start, 1
            for _ in range(d_max - 1):
                reached = {}
                for path in front:
                    for b in links[path[-1]]:
                        if b not in done:
                            reached[b] = min(reached.get(b, path + [b]), path + [b])
                done |= reached
                front = list(reached.values())
                for path in front:
                    yield ">".join(path), len(path)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(x: pd.Series) -> np.ndarray:
    """Grouped: the element-wise sum; a group meets in one task, so ``vectors.vector_sum`` is the form for large groups."""
    return np.sum(np.stack(x.to_list()).astype(float), axis=0) if len(x) else np.zeros(0)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_mean(x: pd.Series) -> np.ndarray:
    """Grouped: the element-wise mean."""
    return np.mean(np.stack(x.to_list()).astype(float), axis=0) if len(x) else np.zeros(0)


#: Expressions under a name: the optimizer puts their bodies into the plan, so they run in generated code.
NATIVE = {
    "vector_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "cosine_sim(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "CASE WHEN vector_dot(a, a) > 0 AND vector_dot(b, b) > 0 THEN vector_dot(a, b) / sqrt(vector_dot(a, a)) / sqrt(vector_dot(b, b)) ELSE 0D END",
    "soft_label(distance DOUBLE, decay DOUBLE) RETURNS DOUBLE": "exp(-decay * distance)",
    "focal_term(p DOUBLE, y DOUBLE) RETURNS DOUBLE": f"0.9D * y * power(1 - least(greatest(p, {EPS}D), 1 - {EPS}D), 2) * -ln(least(greatest(p, {EPS}D), 1 - {EPS}D)) + 0.1D * (1 - y) * power(least(greatest(p, {EPS}D), 1 - {EPS}D), 2) * -ln(1 - least(greatest(p, {EPS}D), 1 - {EPS}D))",
}


def register(spark: SparkSession) -> None:
    for head, body in NATIVE.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    for name, f in (("encode_text", encode_text), ("average_precision", average_precision), ("vector_sum", vector_sum), ("vector_mean", vector_mean)):
        spark.udf.register(name, f)
    spark.udtf.register("shortest_views", ShortestViews)


def register_model(spark: SparkSession, models: DataFrame, name: str = "mlp_score") -> None:
    """``name(x)``: an array of the outputs of one model, averaged over its folds (rows of ``models`` with the same outputs; read on the driver, sent to every task)."""
    rows = models.collect()
    shared = spark.sparkContext.broadcast([Mlp.from_bytes(tuple(r["dims"]), r["weights"]) for r in rows])

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for x in batches:
            flat = np.array(x.to_list(), float).reshape(len(x), -1)
            yield pd.Series(list(np.mean([net.forward(flat)[0] for net in shared.value], axis=0)) if len(x) else [], dtype=object)

    spark.udf.register(name, score)


def register_matcher(spark: SparkSession, cat: Catalog, models: DataFrame, kind: str, *, encoder: Encoder, column_ser: str = "VALS") -> None:
    """Table functions over a catalog and its models (metadata and weights, read on the driver).

    ``candidate_tables(text, target)``: table_id, p, rank of a column's sentence; for PAIR models the sentence's schema is not known, so it takes HOLO or SINGLE.
    ``match_schemas(src, tgt, t, k)``: column_id, target_column, cosine, rank of the k best columns within the t predicted tables.
    """
    if kind == "PAIR":
        raise ValueError("a sentence alone does not name a pair of schemas")
    grouped: dict[str, list[dict]] = {}
    for r in models.filter("run = 0").collect():
        grouped.setdefault(r["model_id"].split("(")[0], []).append(r.asDict())

    class CandidateTables:
        def __init__(self):
            self.folds = {}

        def eval(self, text: str, target: str):
            base = predict.base_of(kind, "", target)
            if base not in grouped:
                return
            folds = self.folds.setdefault(base, predict.Folds(grouped[base]))
            for _, tables, p in folds.answer(encoder.vector(text or "")[None].astype(float), target):
                for rank, (value, table) in enumerate(sorted(zip((-np.round(p[0], 6)).tolist(), tables, strict=True)), 1):
                    yield table, -value, rank

    spark.udtf.register("candidate_tables", F.udtf(CandidateTables, returnType="table_id string, p double, rank int"))
    pipeline.predict_tables(cat, models, kind, encoder=encoder).filter("run = 0").createOrReplaceTempView("predicted_tables")
    rows = augment.build(cat, d_max=1, kind=column_ser, encoder=encoder).select("schema_id", F.col("origin_table").alias("table_id"), "column_id", F.col("x").cast("array<double>").alias("x"))
    cut(rows).createOrReplaceTempView("column_vectors")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION match_schemas(src STRING, tgt STRING, t INT, k INT) RETURNS TABLE (column_id STRING, target_column STRING, cosine DOUBLE, rank INT) RETURN "
        "SELECT * FROM (SELECT s.column_id, c.column_id AS target_column, round(cosine_sim(s.x, c.x), 6) AS cosine, row_number() OVER (PARTITION BY s.column_id ORDER BY round(cosine_sim(s.x, c.x), 6) DESC, c.column_id) AS rank"
        " FROM column_vectors s JOIN predicted_tables p ON p.column_id = s.column_id AND p.target_schema = match_schemas.tgt AND p.rank <= match_schemas.t JOIN column_vectors c ON c.schema_id = p.target_schema AND c.table_id = p.table_id"
        " WHERE s.schema_id = match_schemas.src) WHERE rank <= match_schemas.k"
    )
