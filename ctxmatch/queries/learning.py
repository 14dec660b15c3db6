"""Queries of the learned models and of the experiments on them."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encode import HashedNgram
from ..models import predict, train
from ..models.mlp import Mlp
from ..operators import baseline, block, match, metrics
from ..plans import augment, graph, paths, pipeline, serialize
from ..plans.cut import cut
from ..sources.scenarios import LARGE
from . import query, sql
from .methods import K_GRID, RECALL_T, directed_truth, four, simdoc_recall, valued

TS = list(range(1, 16))
WIDTHS = (64, 8, 4, 10)


def fixed_weight(layer: int, i, j, fold: int = 0):
    """The closed-form weights of the tiny network: eighths, which models store exactly."""
    return ((31 * i + 17 * j + 7 * layer + 5 * fold) % 13 - 6) / 8


def _forward_sql(folds: int = 1) -> str:
    """CTEs up to out(vec_id, target_schema, table_id, p): outputs 0 to 5 are tables of the schema ``low``, the others of ``high``."""
    parts = [f"folds AS (SELECT f.f FROM range(0, {folds}) AS f(f))"]
    for layer, width in enumerate(WIDTHS[1:]):
        before = "SELECT f, vec_id, generate_subscripts(embedding, 1) - 1 AS i, unnest(embedding)::DOUBLE AS v FROM embeddings, folds" if layer == 0 else f"SELECT f, vec_id, j AS i, greatest(z, 0) AS v FROM z{layer - 1}"
        parts.append(f"a{layer} AS ({before}), z{layer} AS (SELECT f, vec_id, j.j, sum(v * (((31 * i + 17 * j.j + 7 * {layer} + 5 * f) % 13 - 6) / 8.0::DOUBLE)) AS z FROM a{layer}, range(0, {width}) AS j(j) GROUP BY f, vec_id, j.j)")
    return ", ".join(parts) + ", out AS (SELECT vec_id, CASE WHEN j < 6 THEN 'low' ELSE 'high' END AS target_schema, 't' || j AS table_id, round(avg(1 / (1 + exp(-z))), 6) AS p FROM z2 GROUP BY vec_id, j)"


def _models(spark, folds: int) -> DataFrame:
    outputs = [f"{'low' if j < 6 else 'high'}.t{j}" for j in range(WIDTHS[-1])]
    rows = []
    for fold in range(folds):
        net = Mlp(WIDTHS)
        net.w = [fixed_weight(layer, np.arange(a)[:, None], np.arange(b)[None], fold) for layer, (a, b) in enumerate(zip(WIDTHS, WIDTHS[1:], strict=False))]
        net.b = [np.zeros(b) for b in WIDTHS[1:]]
        rows.append(("HOLO", fold, 0, list(WIDTHS), outputs, net.to_bytes(), 0.0, []))
    return spark.createDataFrame(rows, train.MODEL)


def _forward(spark, sf_dir, folds: int = 1, targets: tuple[str, ...] = ("low", "high")):
    """The tiny network through the predictor: embeddings are the columns of a schema ``vec``."""
    columns = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.lit("vec").alias("schema_id"), F.col("vec_id").cast("string").alias("column_id"), F.col("embedding").alias("x"))
    found = predict.scores(columns, _models(spark, folds), "HOLO", spark.createDataFrame([("vec", t) for t in targets], "source_schema string, target_schema string"))
    return found.withColumn("p", F.round("p", 6))


def _named(found):
    return found.withColumn("vec_id", F.col("column_id").cast("long")).drop("run", "source_schema", "column_id")


@query(f"WITH {_forward_sql()} SELECT vec_id, target_schema, table_id, p FROM out")
def mlp_forward(spark, sf_dir):
    return _named(_forward(spark, sf_dir))


@query(f"WITH {_forward_sql()} SELECT * FROM (SELECT vec_id, target_schema, table_id, p, row_number() OVER (PARTITION BY vec_id, target_schema ORDER BY p DESC, table_id)::INT AS rank FROM out) WHERE rank <= 4")
def mlp_topt(spark, sf_dir):
    return _named(predict.top_tables(_forward(spark, sf_dir), 4))


@query(f"WITH {_forward_sql()} SELECT vec_id, target_schema, table_id, p FROM out WHERE target_schema = 'high'")
def slice_target(spark, sf_dir):
    """Outputs of one schema only."""
    return _named(_forward(spark, sf_dir, targets=("high",)))


@query(f"WITH {_forward_sql()} SELECT vec_id, target_schema, table_id, p FROM out WHERE p >= 0.5")
def threshold_tables(spark, sf_dir):
    return _named(predict.above(_forward(spark, sf_dir), 0.5))


@query(f"WITH {_forward_sql(3)} SELECT vec_id, target_schema, table_id, p FROM out")
def ensemble_mean(spark, sf_dir):
    """The mean of three fold models of different weights."""
    return _named(_forward(spark, sf_dir, folds=3))


@query(f"WITH {_forward_sql(3)} SELECT vec_id, (substr(table_id, 2)::INT) AS pos, p FROM out")
def udf_mlp_score(spark, sf_dir):
    """The folds' mean as a SQL function of a vector."""
    from ..functions.registered import register_model

    register_model(spark, _models(spark, 3))
    spark.read.parquet(f"{sf_dir}/embeddings.parquet").createOrReplaceTempView("embeddings")
    return spark.sql("SELECT vec_id, pos, round(p, 6) AS p FROM (SELECT vec_id, mlp_score(embedding) AS x FROM embeddings) LATERAL VIEW posexplode(x) AS pos, p")


def _matcher(spark, sf_dir):
    from ..functions.registered import register, register_matcher

    cat, encoder = valued(spark, sf_dir), HashedNgram(256)
    register(spark)
    register_matcher(spark, cat, pipeline.learn(cat, "HOLO", 2, encoder=encoder), "HOLO", encoder=encoder)


@query()
def udtf_candidate_tables(spark, sf_dir):
    """Tables of ``rental`` for a sentence that names no known column."""
    _matcher(spark, sf_dir)
    return spark.sql("SELECT * FROM candidate_tables('[CLS] column customer_name [SEP] table customer [SEP] type string', 'rental')")


@query()
def sql_match_schemas(spark, sf_dir):
    _matcher(spark, sf_dir)
    return spark.sql("SELECT * FROM match_schemas('star', 'desk', 4, 10)")


#: The learned models of the comparison, and how often each is trained with other seeds.
METHODS = (("SINGLE", 2), ("PAIR", 1), ("PAIR", 2), ("HOLO", 1), ("HOLO", 2))
RUNS = 10
_KEPT: dict[tuple, DataFrame] = {}


def kept(spark, sf_dir: str, name: str, make) -> DataFrame:
    """An experiment's rows, computed once for the tables of a folder in an application: what derives from them reads them again."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        _KEPT[key] = cut(make())
    return _KEPT[key]


def predicted(spark, sf_dir: str, kind: str, depth: int) -> DataFrame:
    """scenario, target, model, run, t, value of ``RUNS`` runs."""
    return kept(spark, sf_dir, f"{kind}({depth})", lambda: pipeline.table_prediction(valued(spark, sf_dir), directed_truth(spark), [(kind, depth)], runs=RUNS, ts=TS))


def compared(spark, sf_dir: str) -> DataFrame:
    """scenario, target, model, t, value: all learned models, mean over runs, and the baseline."""
    out = simdoc_recall(spark).select(F.concat_ws("-", "source_schema", "target_schema").alias("scenario"), F.col("target_schema").alias("target"), F.lit("SIMDOC").alias("model"), "t", F.col("recall").alias("value"))
    for kind, depth in METHODS:
        out = out.union(predicted(spark, sf_dir, kind, depth).groupBy("scenario", "target", "model", "t").agg(F.avg("value").alias("value")))
    return out


for _kind, _depth in METHODS:
    query(name=f"train_{_kind.lower()}_d{_depth}")(lambda spark, sf_dir, k=_kind, d=_depth: metrics.over_runs(predicted(spark, sf_dir, k, d), ["scenario", "model", "t"]))


@query()
def table_prediction_runs(spark, sf_dir):
    """Mean and deviation over runs of every model, with the baseline's rows: scenario, model, t, mean, std."""
    rows = simdoc_recall(spark).select(F.concat_ws("-", "source_schema", "target_schema").alias("scenario"), F.lit("SIMDOC").alias("model"), "t", F.col("recall").alias("value"))
    for kind, depth in METHODS:
        rows = rows.union(predicted(spark, sf_dir, kind, depth).select("scenario", "model", "t", "value"))
    return metrics.over_runs(rows, ["scenario", "model", "t"])


@query()
def table_prediction_means(spark, sf_dir):
    return metrics.group_means(compared(spark, sf_dir), LARGE)


@query()
def table_prediction_gain(spark, sf_dir):
    """Gain of each model's group mean over the baseline."""
    rows = metrics.group_means(compared(spark, sf_dir), LARGE)
    base = rows.filter("model = 'SIMDOC'").select("group", "t", F.col("value").alias("base"))
    return rows.filter("model <> 'SIMDOC'").join(base, ["group", "t"]).select("group", "model", "t", metrics.gain(F.col("value"), F.col("base")).alias("gain"))


@query()
def table_prediction_podium(spark, sf_dir):
    return metrics.podium(compared(spark, sf_dir), ["scenario", "t"])


@query()
def minority_schema(spark, sf_dir):
    """How pair models and the shared one fare where the specialised large schema is the target: scenario, t, pair, holo, difference."""
    rows = compared(spark, sf_dir).filter(F.col("target") == LARGE)
    side = lambda m, name: rows.filter(F.col("model") == m).select("scenario", "t", F.round("value", 6).alias(name))
    return side("PAIR(2)", "pair").join(side("HOLO(2)", "holo"), ["scenario", "t"]).withColumn("difference", F.round(F.col("pair") - F.col("holo"), 6))


def _shares(spark, kind: str) -> DataFrame:
    truth = directed_truth(spark).withColumn("scenario", F.concat_ws("-", "source_schema", "target_schema"))
    return truth.groupBy("scenario").agg(F.avg((F.col("kind") == kind).cast("double")).alias("share"))


@query(f"WITH RECURSIVE {sql.SIMDOC}, {sql.TRUTH}, {RECALL_T}, share AS (SELECT source_schema, target_schema, avg(CASE WHEN kind = 'direct' THEN 1.0::DOUBLE ELSE 0 END) AS share FROM truth GROUP BY ALL) SELECT round(corr(share, recall), 6) AS correlation FROM recall JOIN share USING (source_schema, target_schema) WHERE t = 1")
def kind_effect(spark, sf_dir):
    """Correlation over scenarios of the baseline's recall at t=1 with the share of direct matches."""
    recalls = simdoc_recall(spark).filter("t = 1").select(F.concat_ws("-", "source_schema", "target_schema").alias("scenario"), F.col("recall").alias("value"))
    return metrics.kind_effect(recalls, _shares(spark, "direct"))


@query()
def kind_gain(spark, sf_dir):
    """Correlation over scenarios of each model's recall less the baseline's with the share of contextual matches: model, t, correlation."""
    rows = compared(spark, sf_dir).filter("t <= 5")
    base = rows.filter("model = 'SIMDOC'").select("scenario", "t", F.col("value").alias("base"))
    gains = rows.filter("model <> 'SIMDOC'").join(base, ["scenario", "t"]).select("scenario", "model", "t", (F.col("value") - F.col("base")).alias("value"))
    return metrics.kind_effect(gains, _shares(spark, "contextual"), ("model", "t"))


@query()
def pipeline_constrained(spark, sf_dir):
    return pipeline.run(valued(spark, sf_dir), t=4, k=10)


@query()
def explain_learned(spark, sf_dir):
    """Best matches with the tables that the shared model suggests, their probabilities, and the path from the first suggestion to the match's table."""
    cat = valued(spark, sf_dir)
    tables = cut(pipeline.predict_tables(cat, pipeline.learn(cat, "HOLO", 2), "HOLO").filter("rank <= 4"))
    found = block.ranked(pipeline.column_cosines(cat, tables.select("column_id", "target_schema", "table_id")), ["column_id", "target_schema"], [F.col("cosine").desc(), F.col("target_column")], 1)
    name = F.concat_ws(">", "column_id", "target_schema").alias("query")
    links = paths.views(graph.edges(cat, "undirected"), cat.tables, 8)
    out = match.explain(found.select(name, F.col("target_column").alias("target"), "cosine"), tables.select(name, "rank", "table_id", "p"), links)
    return out.select("query", "target", "cosine", "within", "link", F.array_join(F.transform("suggested", lambda s: F.concat(s["table_id"], F.lit(" "), s["p"].cast("string"))), ", ").alias("suggested"))


def ablated(spark, sf_dir: str) -> DataFrame:
    return kept(spark, sf_dir, "ablation", lambda: pipeline.ablation(valued(spark, sf_dir), directed_truth(spark), ts=TS, ks=K_GRID))


@query()
def ablation_holo(spark, sf_dir):
    return ablated(spark, sf_dir)


def _measured(spark, sf_dir: str) -> DataFrame:
    """source_schema, target_schema, k, t, measure, value."""
    return ablated(spark, sf_dir).unpivot(["source_schema", "target_schema", "k", "t"], ["recall", "map"], "measure", "value")


@query()
def break_even(spark, sf_dir):
    """The smallest t from which the constrained recall, and mAP, is at least that of the full search."""
    return metrics.break_even_t(_measured(spark, sf_dir), ["source_schema", "target_schema", "k", "measure"])


@query()
def full_recall_constrained_only(spark, sf_dir):
    """The k at which all matches are found within predicted tables (t: the smallest number of them) though not by the full search."""
    return metrics.only_constrained(_measured(spark, sf_dir).filter("measure = 'recall'").drop("measure"), ["source_schema", "target_schema", "k"])


@query()
def grid_alpha(spark, sf_dir):
    """Validation score of the focal weight: alpha, score (top 1), recall_3."""
    cat, out = valued(spark, sf_dir), None
    for alpha in (0.25, 0.5, 0.75, 0.9, 0.95):
        rows = pipeline.learn(cat, "HOLO", 2, config=replace(pipeline.QUICK, alpha=alpha)).agg(F.round(F.avg("score"), 6).alias("score"), F.round(F.avg(F.col("recalls")[2]), 6).alias("recall_3")).select(F.lit(alpha).alias("alpha"), "score", "recall_3")
        out = rows if out is None else out.union(rows)
    return out


@query()
def select_serialization(spark, sf_dir):
    """Validation score of each serialization for table learning."""
    cat, out = valued(spark, sf_dir), None
    for kind in serialize.KINDS:
        rows = pipeline.learn(cat, "HOLO", 2, table_ser=kind).agg(F.round(F.avg("score"), 6).alias("score"), F.round(F.avg(F.col("recalls")[2]), 6).alias("recall_3")).select(F.lit(kind).alias("kind"), "score", "recall_3")
        out = rows if out is None else out.union(rows)
    return out


@query()
def validation_scores(spark, sf_dir):
    """Held-out recall of the origin table at t, mean and deviation over folds: model, t, mean, std."""
    cat, out = valued(spark, sf_dir), None
    for kind, depth in METHODS:
        rows = pipeline.learn(cat, kind, depth).select(F.lit(f"{kind}({depth})").alias("model"), F.posexplode("recalls").alias("t", "value")).withColumn("t", F.col("t") + 1)
        out = rows if out is None else out.union(rows)
    return metrics.over_runs(out, ["model", "t"])


def _variants(spark, sf_dir: str, variants: dict[str, dict]) -> DataFrame:
    """variant, t, value: mean recall over the scenarios of the shared model."""
    cat, truth, out = valued(spark, sf_dir), directed_truth(spark), None
    for name, options in variants.items():
        rows = pipeline.table_prediction(cat, truth, [("HOLO", options.pop("depth", 2))], ts=TS, **options).groupBy("t").agg(F.round(F.avg("value"), 6).alias("value")).select(F.lit(name).alias("variant"), "t", "value")
        out = rows if out is None else out.union(rows)
    return out


@query()
def augmentation_modes(spark, sf_dir):
    """Recall of the shared model with directed, inverse and undirected views, and with deeper ones."""
    modes = {"directed 2": {}, "inverse 2": {"mode": "inverse"}, "undirected 2": {"mode": "undirected"}, "directed 1": {"depth": 1}, "directed 3": {"depth": 3}, "undirected 3": {"mode": "undirected", "depth": 3}}
    return _variants(spark, sf_dir, modes)


@query()
def label_variants(spark, sf_dir):
    """Recall of the shared model trained on soft, one-hot and multi-hot labels, with the focal loss and with binary cross-entropy."""
    bce = replace(pipeline.QUICK, loss="bce")
    return _variants(spark, sf_dir, {"soft focal": {}, "soft bce": {"config": bce}, "onehot focal": {"label": "onehot"}, "onehot bce": {"label": "onehot", "config": bce}, "multihot focal": {"label": "multihot"}})


@query()
def deep_counterpart(spark, sf_dir):
    """How the rank of a table three joins away moves with the depth of augmentation: the columns of ``star.region`` and ``dealer.offices`` in ``rental.continents``."""
    cat, out = valued(spark, sf_dir), None
    for depth in (1, 2, 3, 4):
        tables = pipeline.predict_tables(cat, pipeline.learn(cat, "HOLO", depth), "HOLO")
        rows = tables.filter("(column_id LIKE 'star.region.%' OR column_id = 'dealer.offices.territory') AND target_schema = 'rental' AND table_id = 'continents'").select(F.lit(depth).alias("depth"), "column_id", "p", "rank")
        out = rows if out is None else out.union(rows)
    return out


_WIDTHS = "w AS (SELECT schema_id AS target_schema, table_id, n_cols FROM tabs), tot AS (SELECT target_schema, sum(n_cols) AS total, count(*) AS tables FROM w GROUP BY 1)"


@query(f"WITH RECURSIVE {sql.SIMDOC}, {_WIDTHS} SELECT target_schema, t::INT AS t, round(avg(1 - kept / total), 6) AS reduction FROM (SELECT s.column_id, s.target_schema, t.t, sum(CASE WHEN rank <= t.t THEN n_cols ELSE 0 END) AS kept FROM simdoc s JOIN w USING (target_schema, table_id), range(1, 16) AS t(t) GROUP BY ALL) JOIN tot USING (target_schema) WHERE t <= tables GROUP BY target_schema, t")
def reduction_columns(spark, sf_dir):
    """The share of a target's columns that the first t tables spare."""
    cat = four(spark)
    return metrics.column_reduction(baseline.table_retrieval(cat), cat.tables.select(F.col("schema_id").alias("target_schema"), "table_id", "n_cols"), TS)


@query(
    f"WITH RECURSIVE {sql.SIMDOC}, {_WIDTHS}, n AS (SELECT schema_id, count(*) AS c FROM cols GROUP BY 1) SELECT target_schema, t::INT AS t, sum(CASE WHEN rank <= t THEN n_cols ELSE 0 END)::BIGINT AS pairs,"
    " any_value((SELECT sum(a.c * b.c) FROM n a JOIN n b ON a.schema_id <> b.schema_id AND b.schema_id = q.target_schema))::BIGINT AS pairs_full FROM (SELECT s.*, w.n_cols, t.t FROM simdoc s JOIN w USING (target_schema, table_id), range(1, 6) AS t(t)) q GROUP BY target_schema, t"
)
def match_cost(spark, sf_dir):
    """Pairs of columns compared within the first t tables, and by the full search: target_schema, t, pairs, pairs_full."""
    cat = four(spark)
    width = cat.tables.select(F.col("schema_id").alias("target_schema"), "table_id", "n_cols")
    rows = baseline.table_retrieval(cat).join(width, ["target_schema", "table_id"]).withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(5))))
    return rows.groupBy("target_schema", "t").agg(F.sum(F.when(F.col("rank") <= F.col("t"), F.col("n_cols")).otherwise(0)).alias("pairs"), F.sum("n_cols").alias("pairs_full"))


@query(
    f"WITH RECURSIVE {sql.catalog_cte(sql.FOUR)}, {sql.views_cte(2)}, {sql.RAC}, r AS (SELECT schema_id, count(*) AS rows FROM rac GROUP BY 1), o AS (SELECT schema_id, count(*) AS tables FROM tabs GROUP BY 1),"
    " s AS (SELECT r.schema_id, rows, tables FROM r JOIN o USING (schema_id)) SELECT 'SINGLE' AS kind, count(*) AS models, sum(rows)::BIGINT AS rows, sum(rows * tables)::BIGINT AS cells FROM s"
    " UNION ALL SELECT 'PAIR', count(*), sum(a.rows + b.rows)::BIGINT, sum((a.rows + b.rows) * (a.tables + b.tables))::BIGINT FROM s a JOIN s b ON a.schema_id < b.schema_id UNION ALL SELECT 'HOLO', 1, sum(rows)::BIGINT, (sum(rows) * sum(tables))::BIGINT FROM s"
)
def training_cost(spark, sf_dir):
    """Models, rows read by them and rows x outputs of each kind of training at depth 2: kind, models, rows, cells."""
    cat = four(spark)
    rows = augment.expand(paths.views(graph.edges(cat), cat.tables, 2), cat).groupBy("schema_id").agg(F.count("*").alias("rows")).join(cat.tables.groupBy("schema_id").agg(F.count("*").alias("tables")), "schema_id")
    models = spark.createDataFrame([(kind, m, s) for kind in train.KINDS for m, own in train.specs(kind, [r[0] for r in cat.tables.select("schema_id").distinct().collect()]).items() for s in own], "kind string, model string, schema_id string")
    per = models.join(rows, "schema_id").groupBy("kind", "model").agg(F.sum("rows").alias("rows"), F.sum("tables").alias("tables"))
    return per.groupBy("kind").agg(F.count("*").alias("models"), F.sum("rows").alias("rows"), F.sum(F.col("rows") * F.col("tables")).alias("cells"))


@query()
def mllib_baseline(spark, sf_dir):
    return train.mllib_baseline(cut(augment.build(four(spark), d_max=2, encoder=HashedNgram(64))))
