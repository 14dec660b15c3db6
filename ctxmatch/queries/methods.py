"""Queries of the methods, baselines and measures that need no training."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import encode, labels, losses, vectors
from ..operators import baseline, block, match, metrics
from ..plans import augment, graph, paths, serialize
from ..plans.cut import cut
from ..sources import catalog, profile, scenarios
from ..sources.scenarios import LARGE, MINI, RESIDUE, SCENARIO, SPECS
from . import query, sql

K_GRID = [1, 2, 3, 5, 10, 20]
_ALL, _FOUR = sql.catalog_cte(sql.ALL), sql.catalog_cte(sql.FOUR)


def all_five(spark: SparkSession) -> catalog.Catalog:
    return catalog.load(spark, sql.ALL)


def four(spark: SparkSession) -> catalog.Catalog:
    return catalog.load(spark, sql.FOUR)


_FOUND = sql.found_cte()


def found(spark: SparkSession, sf_dir: str) -> catalog.Catalog:
    """The catalog of the retail tables with keys and references found in their rows, anew for each query."""
    return catalog.from_data(spark, "given", {t: df.select([c for c, _ in sql.FOUND[t]]) for t, df in _given(spark, sf_dir, sql.FOUND).items()})


def joined(c: str) -> F.Column:
    return F.array_join(c, ",").alias(c)


_SNAPSHOTS: dict[tuple[str, str], DataFrame] = {}


def valued(spark: SparkSession, sf_dir: str) -> catalog.Catalog:
    """The four scenario catalogs with sampled values: a snapshot, taken once for the tables of a folder in an application and reused by its queries."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _SNAPSHOTS:
        scenarios.register(spark, sf_dir)
        _SNAPSHOTS[key] = cut(catalog.sample_values(spark, sql.FOUR, RESIDUE))
    return catalog.with_values(catalog.load(spark, sql.FOUR), _SNAPSHOTS[key])


# ---- catalog and graph


@query(f"WITH {_FOUND} SELECT schema_id, count(DISTINCT table_id) AS tables, count(*) AS columns, count(*) FILTER (is_pk) AS keys, count(fk_table) AS refs FROM cols GROUP BY schema_id")
def catalog_counts(spark, sf_dir):
    return found(spark, sf_dir).columns.groupBy("schema_id").agg(F.count_distinct("table_id").alias("tables"), F.count("*").alias("columns"), F.count(F.when(F.col("is_pk"), 1)).alias("keys"), F.sum(F.size("fk_refs")).alias("refs"))


@query(f"WITH {_FOUND} SELECT * FROM refs")
def catalog_valid_refs(spark, sf_dir):
    return found(spark, sf_dir).refs


def _given(spark, sf_dir, names) -> dict[str, DataFrame]:
    return {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in names}


#: All columns of the retail tables.
STAR = {t: [c for x, c, *_ in SPECS["star"].columns if x == t] for t in SPECS["star"].tables}


@query(" UNION ALL ".join(f"SELECT '{t}' AS table_id, '{c}' AS column_name, count({c}) AS n_rows, count(DISTINCT {c}) AS n_distinct, count(*) = count(DISTINCT {c}) AS is_key FROM {t}" for t, cs in STAR.items() for c in cs))
def profile_keys(spark, sf_dir):
    out = None
    for t, df in _given(spark, sf_dir, STAR).items():
        rows = profile.unique_counts(df.select(*STAR[t]), t)
        out = rows if out is None else out.union(rows)
    return out


def _pairs_sql() -> str:
    single = " UNION ALL ".join(f"SELECT '{t}' AS t, '{c}' AS c, count(*) = count(DISTINCT {c}) AS k, count(*) = count({c}) AS whole FROM {t}" for t, cs in STAR.items() for c in cs)
    double = " UNION ALL ".join(f"SELECT '{t}' AS t, '{x}' AS a, '{y}' AS b, count(*) = count(DISTINCT ({x}, {y})) AS k FROM {t}" for t, cs in STAR.items() for x, y in combinations(cs, 2))
    return f"WITH s AS ({single}), d AS ({double}) SELECT t AS table_id, c AS columns, 1 AS arity FROM s WHERE k AND whole UNION ALL SELECT d.t, a || ',' || b, 2 FROM d JOIN s x ON x.t = d.t AND x.c = a AND x.whole AND NOT x.k JOIN s y ON y.t = d.t AND y.c = b AND y.whole AND NOT y.k WHERE d.k"


@query(_pairs_sql())
def profile_key_sets(spark, sf_dir):
    """Minimal keys of one or two columns of the retail tables."""
    out = None
    for t, df in _given(spark, sf_dir, STAR).items():
        rows = profile.candidate_keys(df.select(*STAR[t])).select(F.lit(t).alias("table_id"), F.array_join("columns", ",").alias("columns"), "arity")
        out = rows if out is None else out.union(rows)
    return out


KEYS = [("nation", "n_nationkey"), ("region", "r_regionkey"), ("customer", "c_custkey"), ("orders", "o_orderkey"), ("supplier", "s_suppkey"), ("part", "p_partkey")]
WEAK = [("nation", "n_regionkey"), ("customer", "c_nationkey"), ("supplier", "s_nationkey"), ("orders", "o_custkey"), ("lineitem", "l_orderkey"), ("lineitem", "l_partkey"), ("lineitem", "l_suppkey"), ("events", "user_id")]
_INCLUSION = [(wt, wc, st, sc) for wt, wc in WEAK for st, sc in KEYS if wt != st]
_WHOLE = [(t, c) for t, cs in STAR.items() for c in cs if next(x[3] for x in SPECS["star"].columns if x[0] == t and x[1] == c) in ("int", "bigint")] + [("events", "event_id"), ("events", "user_id")]


def _orphans_sql(wt: str, wc: str, st: str, sc: str) -> str:
    return f"(SELECT count(DISTINCT {wc}) FROM {wt} WHERE {wc} NOT IN (SELECT {sc} FROM {st}))"


@query(" UNION ALL ".join(f"SELECT '{wt}' AS weak_table, '{wc}' AS weak_column, '{st}' AS strong_table, '{sc}' AS strong_column, {_orphans_sql(wt, wc, st, sc)} AS orphans" for wt, wc, st, sc in _INCLUSION))
def profile_inclusions(spark, sf_dir):
    return profile.orphans(_given(spark, sf_dir, {t for pair in _INCLUSION for t in pair[::2]}), _INCLUSION)


@query("SELECT weak_table, weak_column, strong_table, strong_column FROM (" + " UNION ALL ".join(f"SELECT '{wt}' AS weak_table, '{wc}' AS weak_column, '{st}' AS strong_table, '{sc}' AS strong_column, {_orphans_sql(wt, wc, st, sc)} AS orphans" for wt, wc in _WHOLE for st, sc in KEYS if wt != st) + ") WHERE orphans = 0")
def profile_references(spark, sf_dir):
    """Columns that could refer to a key: among all whole-numbered columns of the retail tables and the events."""
    wanted = {t: [c for x, c in _WHOLE if x == t] for t in dict.fromkeys(t for t, _ in _WHOLE)}
    return profile.references({t: df.select(*wanted[t]) for t, df in _given(spark, sf_dir, wanted).items()}, KEYS)


def _samples(schema: str, table: str):
    residue = RESIDUE[schema]
    text = f"WITH {sql.values_cte([_only(schema, table)])} SELECT x.c AS column_id, _n AS pos, x.v AS value FROM cells"

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        scenarios.register(spark, sf_dir)
        return catalog.sample_rows(spark.sql(scenarios.derived_sql(schema, table)), schema, table, residue)

    query(text, f"sample_values_{schema}_{table}")(run)


def _only(schema: str, table: str):
    spec = SPECS[schema]
    return scenarios.Schema(schema, {table: spec.tables[table]}, [c for c in spec.columns if c[0] == table], [])


for _s, _t in (("star", "customer"), ("star", "orders"), ("desk", "deliveries"), ("dealer", "receipts"), ("rental", "titles")):
    _samples(_s, _t)

for _mode in graph.MODES:
    query(f"WITH {_ALL}, {sql.edges_cte((_mode,))} SELECT schema_id, src, dst FROM edges", f"graph_{_mode}")(lambda spark, sf_dir, m=_mode: graph.edges(all_five(spark), m))


@query(f"WITH {_ALL}, {sql.NEIGHBOURS} SELECT schema_id, table_id, array_to_string(weak, ',') AS weak, array_to_string(strong, ',') AS strong FROM near")
def graph_neighbours(spark, sf_dir):
    return graph.neighbours(all_five(spark)).select("schema_id", "table_id", joined("weak"), joined("strong"))


# ---- views and augmented columns

_VIEW = "SELECT schema_id, array_to_string(path, '>') AS view_id, len(path)::INT AS n_tables FROM views"
for _mode, _d in (("directed", 1), ("directed", 2), ("directed", 3), ("directed", 4), ("inverse", 3), ("undirected", 3)):
    query(f"WITH RECURSIVE {_ALL}, {sql.views_cte(_d, (_mode,))} {_VIEW}", f"views_{_mode}_d{_d}")(
        lambda spark, sf_dir, m=_mode, d=_d: (c := all_five(spark)) and paths.views(graph.edges(c, m), c.tables, d).select("schema_id", "view_id", "n_tables")
    )
_TIE = sql.catalog_cte([MINI["mini_tie"]])


@query(f"WITH RECURSIVE {_TIE}, {sql.views_cte(3, ties='all')} SELECT array_to_string(path, '>') AS view_id, len(path)::INT AS n_tables FROM views")
def views_ties_all(spark, sf_dir):
    c = catalog.load(spark, [MINI["mini_tie"]])
    return paths.views(graph.edges(c), c.tables, 3, ties="all").select("view_id", "n_tables")


@query(f"WITH RECURSIVE {_ALL}, {sql.views_cte(3, ('undirected',))} SELECT schema_id, array_to_string(path, '>') AS view_id FROM views WHERE path <= list_reverse(path)")
def views_undirected_dedup(spark, sf_dir):
    c = all_five(spark)
    return paths.views(graph.edges(c, "undirected"), c.tables, 3, dedup_orientation=True).select("schema_id", "view_id")


@query(f"WITH RECURSIVE {_ALL}, {sql.views_cte(4)} SELECT schema_id, len(path)::INT AS depth, count(*) AS pairs FROM views GROUP BY ALL")
def view_estimate(spark, sf_dir):
    c = all_five(spark)
    return paths.estimate(graph.edges(c), c.tables, 4)


def _materialised(path: list[str]):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        c = catalog.load(spark, [SPECS["star"]])
        view = paths.materialise(path, c, lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet"))
        return view.groupBy(F.col("`customer.c_mktsegment`").alias("segment")).agg(F.count("*").alias("n"), F.count_distinct("`orders.o_orderkey`").alias("orders"), F.round(F.sum(F.col("`customer.c_acctbal`").cast("decimal(18,2)")).cast("double"), 2).alias("balance"))

    return run


_JOINED = "SELECT c_mktsegment AS segment, count(*) AS n, count(DISTINCT o_orderkey) AS orders, round(sum(c_acctbal::DECIMAL(18,2))::DOUBLE, 2) AS balance FROM {} GROUP BY 1"
query(_JOINED.format("customer JOIN orders ON c_custkey = o_custkey"), "view_materialise_customer_orders")(_materialised(["customer", "orders"]))
query(_JOINED.format("nation JOIN customer ON n_nationkey = c_nationkey JOIN orders ON c_custkey = o_custkey"), "view_materialise_nation_customer_orders")(_materialised(["nation", "customer", "orders"]))
_V2 = f"WITH RECURSIVE {_ALL}, {sql.views_cte(2)}, {sql.RAC}"


@query(f"{_V2} SELECT schema_id, view_id, view_name, origin_table, column_name FROM rac")
def rac_skeleton_d2(spark, sf_dir):
    c = all_five(spark)
    return augment.expand(paths.views(graph.edges(c), c.tables, 2), c).select("schema_id", "view_id", "view_name", "origin_table", "column_name")


@query(f"WITH RECURSIVE {_ALL}, {sql.views_cte(2)}, {sql.NEIGHBOURS}, {sql.CONTEXT} SELECT schema_id, view_id, array_to_string(weak, ',') AS weak, array_to_string(strong, ',') AS strong FROM ctx")
def rac_context_d2(spark, sf_dir):
    c = all_five(spark)
    return augment.context(paths.views(graph.edges(c), c.tables, 2), c).select("schema_id", "view_id", joined("weak"), joined("strong"))


@query(f'WITH {_FOUND} SELECT column_id, {sql.CONSTRAINT} AS "constraint" FROM cols')
def constraint_text(spark, sf_dir):
    return found(spark, sf_dir).columns.select("column_id", augment.constraint_text().alias("constraint"))


@query(
    f"WITH RECURSIVE {_FOUND}, {sql.views_cte(7, graph.MODES)}, per AS (SELECT v.schema_id, v.mode, len(v.path) AS n, count(*) AS views, sum((SELECT sum(n_cols) FROM tabs t WHERE t.schema_id = v.schema_id AND list_contains(v.path, t.table_id))) AS columns FROM views v GROUP BY ALL)"
    " SELECT p.schema_id, p.mode, d.d::INT AS depth, sum(views)::BIGINT AS views, sum(columns)::BIGINT AS columns FROM per p JOIN range(1, 8) AS d(d) ON p.n <= d.d GROUP BY ALL"
)
def augmentation_statistics(spark, sf_dir):
    return augment.statistics(found(spark, sf_dir))


_FROM = "FROM rac JOIN ctx USING (schema_id, view_id) LEFT JOIN vals USING (column_id)"
_RECURSIVE_FOUR = f"WITH RECURSIVE {_FOUR}"
for _kind in serialize.KINDS:
    query(
        f"{_RECURSIVE_FOUR}, {sql.views_cte(2)}, {sql.NEIGHBOURS}, {sql.CONTEXT}, {sql.RAC}, {sql.values_cte(sql.FOUR) if _kind != 'META' else 'vals(column_id, v) AS (SELECT NULL, [NULL] WHERE false)'} SELECT schema_id, view_id, column_id, {sql.sentence(_kind)} AS text {_FROM}",
        f"ser_{_kind.lower()}",
    )(lambda spark, sf_dir, k=_kind: augment.build(valued(spark, sf_dir) if k != "META" else four(spark), d_max=2, kind=k).select("schema_id", "view_id", "column_id", "text"))


@query(f"{_RECURSIVE_FOUR}, {sql.views_cte(1)}, {sql.RAC} SELECT column_id, array_to_string(string_split(column_name || ' ' || view_name || ' ' || dtype || ' ' || coalesce(con, ''), ' ')[1:3], ' ') AS text FROM rac")
def ser_options(spark, sf_dir):
    """Sentences without words that name their parts, without marks, cut after three tokens."""
    return augment.build(four(spark), d_max=1, kind="META", options=serialize.Options(anchors=False, marks=False, tokens=3)).select("column_id", "text")


@query(f"WITH {_ALL}, {sql.TABDOC} SELECT * FROM tabdoc")
def ser_tabdoc(spark, sf_dir):
    return serialize.table(all_five(spark))


@query(f"WITH {sql.buckets('conversations', 'conv_id, turn')} SELECT conv_id, turn, bucket, round(value, 6) AS value FROM hash")
def encode_wordhash(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    return encode.word_buckets(rows, ["conv_id", "turn"], "text").select("conv_id", "turn", "bucket", F.round("value", 6).alias("value"))


@query("SELECT vec_id, round(embedding[1]::DOUBLE, 6) AS dim0, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def encode_precomputed(spark, sf_dir):
    vecs = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    rows = encode.Precomputed(vecs, "vec_id", "embedding").transform(vecs.select("vec_id"), "vec_id", "x")
    return rows.select("vec_id", F.round(F.col("x")[0].cast("double"), 6).alias("dim0"), F.round(vectors.norm(F.col("x")), 6).alias("norm"))


def _label_rows(spark, y, d=2):
    c = all_five(spark)
    rows = augment.expand(paths.views(graph.edges(c), c.tables, d), c)
    return rows.select("view_id", "column_id", F.explode(y).alias("table_id", "weight")).select("view_id", "column_id", "table_id", F.round("weight", 6).alias("weight"))


def _label_sql(weight: str, where: str = "true", d: int = 2) -> str:
    return f"WITH RECURSIVE {_ALL}, {sql.views_cte(d)}, {sql.RAC}, cell AS (SELECT view_id, column_id, position, unnest(path) AS table_id, generate_subscripts(path, 1) - 1 AS i FROM rac) SELECT view_id, column_id, table_id, round({weight}, 6) AS weight FROM cell WHERE {where}"


@query(_label_sql("exp(-0.5::DOUBLE * abs(i - position))", d=3))
def soft_labels_d3(spark, sf_dir):
    return _label_rows(spark, labels.soft(F.col("path"), F.col("position")), 3)


@query(_label_sql("exp(-0.5::DOUBLE * abs(i - position))"))
def soft_labels_d2(spark, sf_dir):
    return _label_rows(spark, labels.soft(F.col("path"), F.col("position")))


@query(_label_sql("1.0::DOUBLE", "i = position"))
def labels_onehot(spark, sf_dir):
    return _label_rows(spark, labels.onehot(F.col("path"), F.col("position")))


@query(_label_sql("1.0::DOUBLE"))
def labels_multihot(spark, sf_dir):
    return _label_rows(spark, labels.multihot(F.col("path")))


@query(" UNION ALL ".join(f"SELECT {x}::DOUBLE AS decay, d.d::INT AS distance, round(exp(-{x}::DOUBLE * d.d), 6) AS weight FROM range(0, 5) AS d(d)" for x in (0.1, 0.3, 0.5, 0.7, 0.9)))
def soft_labels_decay_sweep(spark, sf_dir):
    path = F.array(*[F.lit(str(i)) for i in range(5)])
    out = None
    for x in (0.1, 0.3, 0.5, 0.7, 0.9):
        rows = spark.range(1).select(F.lit(x).alias("decay"), F.explode(labels.soft(path, F.lit(0), x)).alias("d", "weight")).select("decay", F.col("d").cast("int").alias("distance"), F.round("weight", 6).alias("weight"))
        out = rows if out is None else out.union(rows)
    return out


@query(f"{_V2} SELECT schema_id, sum(len(path))::BIGINT AS positives, (count(*) * (SELECT count(*) FROM tabs t WHERE t.schema_id = rac.schema_id))::BIGINT AS cells, round(sum(len(path)) / (count(*) * (SELECT count(*) FROM tabs t WHERE t.schema_id = rac.schema_id)), 6) AS share FROM rac GROUP BY schema_id")
def label_sparsity(spark, sf_dir):
    c = all_five(spark)
    rows = augment.expand(paths.views(graph.edges(c), c.tables, 2), c).withColumn("y", labels.soft(F.col("path"), F.col("position")))
    return metrics.sparsity(rows.select("schema_id", "y"), c.tables.groupBy("schema_id").agg(F.count("*").alias("n")))


# ---- losses


def _scored_labels(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/labels.parquet")
    p = (F.pmod(F.col("doc_id") * 37, F.lit(100)) + 0.5) / 100
    return rows.select("doc_id", p.alias("p"), F.explode(F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array(F.col("quality"), F.col("toxic")))).alias("label", "y")).withColumn("y", F.col("y").cast("double"))


_SCORED = "s AS (SELECT doc_id, ((doc_id * 37) % 100 + 0.5::DOUBLE) / 100 AS p, unnest(['quality', 'toxic']) AS label, unnest([quality, toxic])::DOUBLE AS y FROM labels)"
_FOCAL = "0.9 * y * pow(1 - p, 2) * -ln(p) + 0.1 * (1 - y) * pow(p, 2) * -ln(1 - p)"


@query(f"WITH {_SCORED} SELECT label, round(avg({_FOCAL}), 6) AS loss FROM s GROUP BY label")
def focal_loss(spark, sf_dir):
    return _scored_labels(spark, sf_dir).groupBy("label").agg(F.round(F.avg(losses.focal(F.col("p"), F.col("y"))), 6).alias("loss"))


@query(f"WITH {_SCORED} SELECT label, round(avg(-(y * ln(p) + (1 - y) * ln(1 - p))), 6) AS loss FROM s GROUP BY label")
def bce_loss(spark, sf_dir):
    return _scored_labels(spark, sf_dir).groupBy("label").agg(F.round(F.avg(losses.bce(F.col("p"), F.col("y"))), 6).alias("loss"))


@query(f"WITH {_SCORED} SELECT label, round(avg({_FOCAL}), 6) AS loss, count(*) AS cells FROM s WHERE (label = 'quality') = (doc_id % 2 = 0) GROUP BY label")
def masked_loss(spark, sf_dir):
    own = (F.col("label") == "quality") == (F.col("doc_id") % 2 == 0)
    cell = losses.masked(losses.focal(F.col("p"), F.col("y")), own)
    return _scored_labels(spark, sf_dir).groupBy("label").agg(F.round(F.avg(cell), 6).alias("loss"), F.count(cell).alias("cells"))


# ---- blocking on vectors


def _sides(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>").alias("x"), "label")
    return rows.filter("vec_id % 2 = 0").withColumnRenamed("vec_id", "query"), rows.filter("vec_id % 2 = 1").withColumnRenamed("vec_id", "neighbour")


_PAIRS = "e AS (SELECT vec_id, embedding::DOUBLE[] AS x, label FROM embeddings), pair AS (SELECT q.vec_id AS query, t.vec_id AS neighbour, q.label AS ql, t.label AS tl, q.x AS qx, t.x AS tx FROM e q, e t WHERE q.vec_id % 2 = 0 AND t.vec_id % 2 = 1)"
_L2 = "ranked AS (SELECT query, neighbour, ql, tl, dist, row_number() OVER (PARTITION BY query ORDER BY dist, neighbour)::INT AS rank FROM (SELECT *, round(list_distance(qx, tx), 6) AS dist FROM pair))"
_COS = "ranked AS (SELECT query, neighbour, dist, row_number() OVER (PARTITION BY query ORDER BY dist DESC, neighbour)::INT AS rank FROM (SELECT *, round(list_cosine_similarity(qx, tx), 6) AS dist FROM pair))"


@query(f"WITH {_PAIRS}, {_L2} SELECT query, neighbour, dist, rank FROM ranked WHERE rank <= 20")
def knn_l2(spark, sf_dir):
    return block.knn(*_sides(spark, sf_dir), 20)


@query(f"WITH {_PAIRS}, {_COS} SELECT query, neighbour, dist, rank FROM ranked WHERE rank <= 20")
def knn_cosine(spark, sf_dir):
    return block.knn(*_sides(spark, sf_dir), 20, metric="cosine")


@query(f"WITH {_PAIRS}, {_L2} SELECT k.k::INT AS k, count(*) AS pairs, round(avg(dist), 5) AS mean_dist FROM ranked JOIN (VALUES (1), (2), (3), (5), (10), (20)) AS k(k) ON rank <= k.k GROUP BY k.k")
def knn_k_grid(spark, sf_dir):
    rows = block.knn(*_sides(spark, sf_dir), 20).withColumn("k", F.explode(F.array(*map(F.lit, K_GRID))))
    return rows.filter("rank <= k").groupBy("k").agg(F.count("*").alias("pairs"), F.round(F.avg("dist"), 5).alias("mean_dist"))


def _nearest_labels(spark, sf_dir, t):
    src, tgt = _sides(spark, sf_dir)
    centroids = vectors.vector_mean(tgt, ["label"], "x", "x").select(F.col("label").alias("neighbour"), "x")
    return block.knn(src.select("query", "x"), centroids, t).select("query", F.col("neighbour").alias("table_id"), F.col("rank").alias("t"))


_CENTROIDS = (
    "cen AS (SELECT label, list(m ORDER BY pos) AS x FROM (SELECT label, pos, avg(v) AS m FROM (SELECT label, unnest(x) AS v, generate_subscripts(x, 1) AS pos FROM e WHERE vec_id % 2 = 1) GROUP BY label, pos) GROUP BY label),"
    " near AS (SELECT query, label AS table_id, row_number() OVER (PARTITION BY query ORDER BY dist, label)::INT AS t FROM (SELECT q.vec_id AS query, c.label, round(list_distance(q.x, c.x), 6) AS dist FROM e q, cen c WHERE q.vec_id % 2 = 0))"
)


@query(f"WITH {_PAIRS}, {_CENTROIDS} SELECT query, neighbour, dist, rank FROM (SELECT p.query, p.neighbour, round(list_distance(qx, tx), 6) AS dist, row_number() OVER (PARTITION BY p.query ORDER BY round(list_distance(qx, tx), 6), p.neighbour)::INT AS rank FROM pair p JOIN near n ON n.query = p.query AND n.table_id = p.tl AND n.t <= 3) WHERE rank <= 20")
def knn_within_tables(spark, sf_dir):
    src, tgt = _sides(spark, sf_dir)
    return block.knn_within(src.select("query", "x"), tgt.select("neighbour", "x", F.col("label").alias("table_id")), _nearest_labels(spark, sf_dir, 3).select("query", "table_id"), 20).select("query", "neighbour", "dist", "rank")


@query()
def lsh_recall(spark, sf_dir):
    """Share of the exact k nearest that hashed blocking finds."""
    src, tgt = _sides(spark, sf_dir)
    exact, found = block.knn(src, tgt, 20), block.lsh(src.select("query", "x"), tgt.select("neighbour", "x"), 20).select("query", "neighbour", F.lit(1).alias("hit"))
    return exact.join(found, ["query", "neighbour"], "left").withColumn("k", F.explode(F.array(*map(F.lit, K_GRID)))).filter("rank <= k").groupBy("k").agg(F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"))


_REL = "rel AS (SELECT q.vec_id AS query, count(*) AS n FROM e q JOIN e t ON q.vec_id % 2 = 0 AND t.vec_id % 2 = 1 AND q.label = t.label GROUP BY 1)"
_KS = "(VALUES (1), (2), (3), (5), (10), (20)) AS k(k)"


def _vector_truth(spark, sf_dir):
    src, tgt = _sides(spark, sf_dir)
    return src.select("query", "label").join(tgt.select("neighbour", "label"), "label").select(F.lit(1).alias("g"), "query", "neighbour")


@query(
    f"WITH {_PAIRS}, {_L2}, {_REL}, h AS (SELECT *, row_number() OVER (PARTITION BY query ORDER BY rank) AS hits FROM ranked WHERE ql = tl),"
    f" ap AS (SELECT r.query, k.k, r.n, coalesce(sum(CASE WHEN h.rank <= k.k THEN h.hits / h.rank END), 0) AS s, count(CASE WHEN h.rank <= k.k THEN 1 END) AS got FROM rel r CROSS JOIN {_KS} LEFT JOIN h ON h.query = r.query GROUP BY ALL)"
    " SELECT k::INT AS k, round(sum(got) / sum(n), 6) AS recall, round(avg(s / least(n, k)), 6) AS map FROM ap GROUP BY k"
)
def vector_recall_map(spark, sf_dir):
    found, truth = block.knn(*_sides(spark, sf_dir), 20).withColumn("g", F.lit(1)), _vector_truth(spark, sf_dir)
    how = {"query": "query", "item": "neighbour", "by": ["g"]}
    return metrics.recall_at(found, truth, K_GRID, cutoff="k", **how).join(metrics.map_at(found, truth, K_GRID, **how), ["g", "k"]).select("k", "recall", "map")


@query(
    f"WITH {_PAIRS}, {_L2}, {_REL}, h AS (SELECT r.query, r.n, k.k, count(x.rank) AS got, min(x.rank) AS first FROM rel r CROSS JOIN {_KS} LEFT JOIN (SELECT * FROM ranked WHERE ql = tl) x ON x.query = r.query AND x.rank <= k.k GROUP BY ALL)"
    " SELECT k::INT AS k, round(avg(got / k), 6) AS precision, round(avg(2 * got / (k + n)), 6) AS f1, round(avg(coalesce(1 / first, 0)), 6) AS mrr FROM h GROUP BY k"
)
def vector_precision_f1_mrr(spark, sf_dir):
    found = block.knn(*_sides(spark, sf_dir), 20).withColumn("g", F.lit(1))
    return metrics.precision_f1_mrr(found, _vector_truth(spark, sf_dir), K_GRID, query="query", item="neighbour", by=["g"], cutoff="k").drop("g")


@query(f"WITH {_PAIRS} SELECT query, neighbour AS target, c AS cosine, row_number() OVER (PARTITION BY query ORDER BY c DESC, neighbour)::INT AS rank FROM (SELECT *, round(list_cosine_similarity(qx, tx), 6) AS c FROM pair WHERE ql = tl)")
def cosine_ranking(spark, sf_dir):
    """Candidates of the query's own label ranked by cosine."""
    src, tgt = _sides(spark, sf_dir)
    return block.cosine_ranks(src, tgt, "label").withColumnsRenamed({"neighbour": "target", "dist": "cosine"})


@query(
    f"WITH {_PAIRS}, {_CENTROIDS}, {_REL}, got AS (SELECT g.t, p.query, p.ql = p.tl AS good, row_number() OVER (PARTITION BY g.t, p.query ORDER BY round(list_distance(qx, tx), 6), p.neighbour) AS rank FROM (VALUES (1), (2), (3), (5), (10)) AS g(t) JOIN near n ON n.t <= g.t JOIN pair p ON p.query = n.query AND p.tl = n.table_id)"
    f" SELECT t::INT AS t, k.k::INT AS k, round(sum(CASE WHEN good AND rank <= k.k THEN 1 ELSE 0 END) / (SELECT sum(n) FROM rel), 6) AS recall FROM got CROSS JOIN {_KS} GROUP BY t, k.k"
)
def vector_constrained(spark, sf_dir):
    src, tgt = _sides(spark, sf_dir)
    # the 20 best of every table once, with the place of the table among the query's; the limits on that place then only choose among them
    near = _nearest_labels(spark, sf_dir, 10).join(src, "query").select(F.struct("query", "t", (F.col("table_id") == F.col("label")).alias("good")).alias("query"), "table_id", "x")
    each = block.nearest_each(near, tgt.select("neighbour", F.col("label").alias("table_id"), "x"), 20).select("query.*", "neighbour", "dist")
    within = each.withColumn("g", F.explode(F.array(*map(F.lit, [1, 2, 3, 5, 10])))).filter("t <= g")
    found = block.ranked(within, ["g", "query"], [F.col("dist"), F.col("neighbour")], 20)
    total = src.groupBy("label").agg(F.count("*").alias("a")).join(tgt.groupBy("label").agg(F.count("*").alias("b")), "label").agg(F.sum(F.col("a") * F.col("b")).alias("total"))
    return metrics.recall_of_hits(found.withColumn("hit", F.col("good")), total, K_GRID, by=["g"], cutoff="k").withColumnRenamed("g", "t")


# ---- the similarity baseline, truth and measures

_SIM = f"WITH RECURSIVE {sql.SIMDOC}"


@query(f"{_SIM} SELECT source_schema, column_id, target_schema, table_id, score, rank::INT AS rank FROM simdoc")
def simdoc_tables(spark, sf_dir):
    return baseline.table_retrieval(four(spark)).select("source_schema", "column_id", "target_schema", "table_id", "score", "rank")


@query(f"WITH {_FOUR} SELECT c.column_id, t.schema_id AS target_schema, t.table_id, row_number() OVER (PARTITION BY c.column_id, t.schema_id ORDER BY md5('0|' || c.column_id || '|' || t.schema_id || '|' || t.table_id), t.table_id)::INT AS rank FROM cols c JOIN tabs t ON c.schema_id <> t.schema_id")
def random_tables(spark, sf_dir):
    return baseline.random_tables(four(spark)).select("column_id", "target_schema", "table_id", "rank")


def directed_truth(spark):
    return scenarios.both_directions(scenarios.truth_frame(spark))


@query(f"WITH {sql.TRUTH} SELECT source_schema, column_id, target_schema, target_column, kind FROM truth")
def truth_pairs(spark, sf_dir):
    return directed_truth(spark)


@query(f"WITH {sql.TRUTH} SELECT * FROM truth_tables")
def truth_tables(spark, sf_dir):
    return metrics.table_truth(directed_truth(spark))


@query(f"WITH {sql.TRUTH} SELECT schema_a || '-' || schema_b AS pair, kind, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY schema_a, schema_b), 6) AS share FROM pairs GROUP BY schema_a, schema_b, kind")
def truth_by_kind(spark, sf_dir):
    from pyspark.sql.window import Window

    rows = scenarios.truth_frame(spark).groupBy(F.concat_ws("-", "schema_a", "schema_b").alias("pair"), "kind").agg(F.count("*").alias("n"))
    return rows.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("pair")), 6))


_TS = list(range(1, 16))
RECALL_T = (
    "found AS (SELECT m.*, s.rank FROM truth_tables m LEFT JOIN simdoc s USING (source_schema, column_id, target_schema, table_id)),"
    " recall AS (SELECT source_schema, target_schema, t.t::INT AS t, round(avg(CASE WHEN rank <= t.t THEN 1.0::DOUBLE ELSE 0 END), 6) AS recall FROM found JOIN range(1, 16) AS t(t) ON t.t <= (SELECT count(*) FROM tabs x WHERE x.schema_id = target_schema) GROUP BY ALL)"
)


def simdoc_recall(spark) -> DataFrame:
    """source_schema, target_schema, t, recall for every t up to the target's tables."""
    cat = four(spark)
    rows = metrics.recall_at(baseline.table_retrieval(cat), metrics.table_truth(directed_truth(spark)), _TS, query="column_id", item="table_id", by=["source_schema", "target_schema"], cutoff="t")
    return rows.join(F.broadcast(cat.tables.groupBy(F.col("schema_id").alias("target_schema")).agg(F.count("*").alias("n"))), "target_schema").filter("t <= n").drop("n")


@query(f"{_SIM}, {sql.TRUTH}, {RECALL_T} SELECT * FROM recall")
def recall_at_t(spark, sf_dir):
    return simdoc_recall(spark).select("source_schema", "target_schema", "t", "recall")


@query(f"{_SIM}, {sql.TRUTH}, {RECALL_T} SELECT source_schema, target_schema, min(CASE WHEN recall >= 1 THEN t END) AS full_t FROM recall GROUP BY ALL")
def full_recall_t(spark, sf_dir):
    return metrics.full_recall_t(simdoc_recall(spark), ["source_schema", "target_schema"])


@query(f"{_SIM}, {sql.TRUTH}, {RECALL_T} SELECT g.g AS \"group\", 'SIMDOC' AS model, t, round(avg(recall), 6) AS value FROM recall JOIN (VALUES ('all'), ('target is large'), ('target is not large')) AS g(g) ON g.g = 'all' OR (g.g = 'target is large') = (target_schema = '{LARGE}') GROUP BY ALL")
def group_means(spark, sf_dir):
    rows = simdoc_recall(spark).select(F.concat_ws("-", "source_schema", "target_schema").alias("scenario"), F.col("target_schema").alias("target"), F.lit("SIMDOC").alias("model"), "t", F.col("recall").alias("value"))
    return metrics.group_means(rows, LARGE)


@query(f"{_SIM}, {sql.TRUTH}, found AS (SELECT m.column_id, m.target_schema, s.rank FROM truth_tables m LEFT JOIN simdoc s USING (source_schema, column_id, target_schema, table_id)), q AS (SELECT column_id, target_schema, t.t, max(CASE WHEN rank <= t.t THEN 1.0::DOUBLE ELSE 0 END) AS a, min(CASE WHEN rank <= t.t THEN 1.0::DOUBLE ELSE 0 END) AS b FROM found, range(1, 5) AS t(t) GROUP BY ALL), p AS (SELECT t.t, avg(CASE WHEN rank <= t.t THEN 1.0::DOUBLE ELSE 0 END) AS v FROM found, range(1, 5) AS t(t) GROUP BY ALL)"
       " SELECT 'pair' AS unit, t::INT AS t, round(v, 6) AS recall FROM p UNION ALL SELECT 'any', t::INT, round(avg(a), 6) FROM q GROUP BY t UNION ALL SELECT 'all', t::INT, round(avg(b), 6) FROM q GROUP BY t")  # fmt: skip
def recall_units(spark, sf_dir):
    sim, truth = baseline.table_retrieval(four(spark)), metrics.table_truth(directed_truth(spark))
    keyed = lambda df: df.withColumn("g", F.lit(1)).withColumn("q", F.concat_ws(">", "column_id", "target_schema"))
    out = None
    for unit in ("pair", "any", "all"):
        rows = metrics.recall_at(keyed(sim), keyed(truth), [1, 2, 3, 4], query="q", item="table_id", by=["g"], cutoff="t", unit=unit).select(F.lit(unit).alias("unit"), "t", "recall")
        out = rows if out is None else out.union(rows)
    return out


@query(f"{_SIM}, {sql.TRUTH}, found AS (SELECT DISTINCT m.source_schema, m.target_schema, m.column_id, m.kind, string_split(m.target_column, '.')[2] AS table_id FROM truth m) SELECT f.kind, t.t::INT AS t, round(avg(CASE WHEN s.rank <= t.t THEN 1.0::DOUBLE ELSE 0 END), 6) AS recall FROM found f LEFT JOIN simdoc s USING (source_schema, column_id, target_schema, table_id), range(1, 6) AS t(t) GROUP BY ALL")
def recall_by_kind(spark, sf_dir):
    truth = directed_truth(spark).select("source_schema", "column_id", "target_schema", F.split("target_column", "[.]")[1].alias("table_id"), "kind").distinct()
    found = truth.join(baseline.table_retrieval(four(spark)), ["source_schema", "column_id", "target_schema", "table_id"], "left").withColumn("t", F.explode(F.sequence(F.lit(1), F.lit(5))))
    return found.groupBy("kind", "t").agg(F.round(F.avg(F.coalesce(F.col("rank") <= F.col("t"), F.lit(False)).cast("double")), 6).alias("recall"))


@query(f"WITH {_FOUR}, n AS (SELECT schema_id AS target_schema, count(*) AS tables FROM tabs GROUP BY 1) SELECT target_schema, t.t::INT AS t, round(greatest(0.0::DOUBLE, 1 - t.t / tables), 6) AS reduction FROM n JOIN range(1, 16) AS t(t) ON t.t <= tables")
def reduction(spark, sf_dir):
    rows = four(spark).tables.groupBy(F.col("schema_id").alias("target_schema")).agg(F.count("*").alias("tables")).withColumn("t", F.explode(F.sequence(F.lit(1), F.col("tables").cast("int"))))
    return rows.select("target_schema", "t", metrics.reduction(F.col("t"), F.col("tables")).alias("reduction"))


@query("SELECT s.s::BIGINT AS n_schemas, s.s::BIGINT AS single, (s.s * (s.s - 1) // 2)::BIGINT AS pair, 1::BIGINT AS holo FROM range(2, 65) AS s(s)")
def model_counts(spark, sf_dir):
    n = F.col("id")
    return spark.range(2, 65).select(n.alias("n_schemas"), n.alias("single"), (n * (n - 1) / 2).cast("long").alias("pair"), F.lit(1).cast("long").alias("holo"))


@query(f"WITH RECURSIVE {_FOUR}, {sql.views_cte(2)}, {sql.RAC}, r AS (SELECT schema_id, origin_table, (row_number() OVER (PARTITION BY schema_id, origin_table ORDER BY md5(view_id || column_id), view_id, column_id) - 1) % 5 AS fold FROM rac) SELECT schema_id, origin_table, fold::INT AS fold, count(*) AS n FROM r GROUP BY ALL")
def folds(spark, sf_dir):
    from ..models.train import with_folds

    c = four(spark)
    rows = augment.expand(paths.views(graph.edges(c), c.tables, 2), c)
    return with_folds(rows).groupBy("schema_id", "origin_table", "fold").agg(F.count("*").alias("n"))


# ---- column matching without a table constraint, and with the baseline's tables

_COLHASH = f"{_SIM}, {sql.TRUTH}, {sql.values_cte(sql.FOUR)}, {sql.NEIGHBOURS}, {sql.CONTEXT}, "


def _column_hash(kind: str, tag: str = "") -> str:
    """CTEs up to cs: the cosine of every two columns of different schemas, 0 where they share no bucket."""
    vt, vh, cs = f"vt{tag}", f"vh{tag}", f"cs{tag}"
    return (
        f"{vt} AS (SELECT schema_id, column_id, {sql.sentence(kind)} AS text {_FROM}), " + sql.buckets(vt, "schema_id, column_id", name=vh) + f", {vh}_dot AS (SELECT a.column_id AS q, b.column_id AS c, sum(a.value * b.value) AS s FROM {vh} a JOIN {vh} b ON a.bucket = b.bucket AND a.schema_id <> b.schema_id GROUP BY ALL),"
        f" {cs} AS (SELECT a.schema_id AS source_schema, a.column_id, b.schema_id AS target_schema, b.column_id AS target_column, {sql.cosine('s')} AS cosine FROM {vt} a JOIN {vt} b ON a.schema_id <> b.schema_id LEFT JOIN {vh}_dot ON q = a.column_id AND c = b.column_id)"
    )


def column_vectors(spark, sf_dir, kind: str, cat=None) -> DataFrame:
    """schema_id, table_id, column_id, x."""
    rac = augment.build(cat or valued(spark, sf_dir), d_max=1, kind=kind).withColumnRenamed("origin_table", "table_id")
    return cut(encode.word_vectors(rac, ["schema_id", "table_id", "column_id"], "text"))


def full_search(vecs: DataFrame, k: int | None) -> DataFrame:
    """source_schema, column_id, target_schema, target_column, cosine, rank: the k nearest columns of every other schema."""
    found = block.knn(vecs.select("schema_id", F.col("column_id").alias("query"), "x"), vecs.select("schema_id", F.col("column_id").alias("neighbour"), "x"), k, metric="cosine", across="schema_id")
    return found.select(F.split("query", "[.]")[0].alias("source_schema"), F.col("query").alias("column_id"), F.col("schema_id").alias("target_schema"), F.col("neighbour").alias("target_column"), F.col("dist").alias("cosine"), "rank")


@query(f"{_COLHASH}{_column_hash('VALS')} SELECT column_id, target_schema, target_column, cosine, rank FROM (SELECT *, row_number() OVER (PARTITION BY column_id, target_schema ORDER BY cosine DESC, target_column)::INT AS rank FROM cs) WHERE rank <= 20")
def fullsearch(spark, sf_dir):
    return full_search(column_vectors(spark, sf_dir, "VALS"), 20).drop("source_schema")


_SWEEP = (
    "got AS (SELECT g.t, c.source_schema, c.column_id, c.target_schema, c.target_column, row_number() OVER (PARTITION BY g.t, c.column_id, c.target_schema ORDER BY cosine DESC, c.target_column) AS rank"
    " FROM cs c JOIN simdoc s ON s.column_id = c.column_id AND s.target_schema = c.target_schema AND s.table_id = string_split(c.target_column, '.')[2] JOIN range(1, 16) AS g(t) ON s.rank <= g.t)"
)


def constrained(vecs: DataFrame, tables: DataFrame, ts: list[int], k: int) -> DataFrame:
    """t, source_schema, column_id, target_schema, target_column, cosine, rank: the k best candidates within the first t predicted tables.

    An equi-join on the table: columns of tables that no t reaches are never compared.
    """
    near = tables.filter(F.col("rank") <= max(ts)).select("column_id", "target_schema", "table_id", F.col("rank").alias("_r"))
    src = vecs.select(F.col("schema_id").alias("source_schema"), "column_id", F.col("x").alias("a"))
    tgt = vecs.select(F.col("schema_id").alias("target_schema"), "table_id", F.col("column_id").alias("target_column"), F.col("x").alias("b"))
    scored = near.join(src, "column_id").join(tgt, ["target_schema", "table_id"]).withColumn("cosine", F.round(vectors.cosine(F.col("a"), F.col("b")), 6) + 0.0)
    rows = scored.withColumn("t", F.explode(F.array(*map(F.lit, ts)))).filter("_r <= t").select("t", "source_schema", "column_id", "target_schema", "target_column", "cosine")
    return block.ranked(rows, ["t", "column_id", "target_schema"], [F.col("cosine").desc(), F.col("target_column")], k)


def sweep(vecs: DataFrame, tables: DataFrame, truth: DataFrame, ts: list[int], ks: list[int]) -> DataFrame:
    """source_schema, target_schema, t, k, recall, map: one scoring, filters after."""
    found = constrained(vecs, tables, ts, max(ks))
    every = truth.drop("kind").withColumn("t", F.explode(F.array(*map(F.lit, ts))))
    how = {"query": "column_id", "item": "target_column", "by": ["source_schema", "target_schema", "t"]}
    return metrics.recall_at(found, every, ks, cutoff="k", **how).join(metrics.map_at(found, every, ks, **how), ["source_schema", "target_schema", "t", "k"])


@query(
    f"{_COLHASH}{_column_hash('VALS')}, {_SWEEP}, rel AS (SELECT source_schema, target_schema, column_id, count(*) AS n FROM truth GROUP BY ALL),"
    " h AS (SELECT g.*, row_number() OVER (PARTITION BY t, g.column_id, g.target_schema ORDER BY rank) AS hits FROM got g JOIN truth m ON m.column_id = g.column_id AND m.target_schema = g.target_schema AND m.target_column = g.target_column WHERE rank <= 20),"
    f" ap AS (SELECT r.source_schema, r.target_schema, r.column_id, r.n, t.t, k.k, coalesce(sum(CASE WHEN h.rank <= k.k THEN h.hits / h.rank END), 0) AS s, count(CASE WHEN h.rank <= k.k THEN 1 END) AS c FROM rel r CROSS JOIN range(1, 16) AS t(t) CROSS JOIN {_KS} LEFT JOIN h ON h.column_id = r.column_id AND h.target_schema = r.target_schema AND h.t = t.t GROUP BY ALL)"
    " SELECT source_schema, target_schema, t::INT AS t, k::INT AS k, round(sum(c) / sum(n), 6) AS recall, round(avg(s / least(n, k)), 6) AS map FROM ap GROUP BY ALL"
)
def pipeline_sweep(spark, sf_dir):
    cat = valued(spark, sf_dir)
    return sweep(column_vectors(spark, sf_dir, "VALS", cat), baseline.table_retrieval(cat), directed_truth(spark), _TS, K_GRID)


@query(f"{_COLHASH}{_column_hash('VALS')}, {_SWEEP} SELECT a.column_id AS column_a, a.target_column AS column_b FROM got a JOIN got b ON b.column_id = a.target_column AND b.target_column = a.column_id AND a.t = 4 AND b.t = 4 AND a.rank <= 2 AND b.rank <= 2 WHERE a.source_schema < a.target_schema")
def symmetric_matches(spark, sf_dir):
    cat = valued(spark, sf_dir)
    found = constrained(column_vectors(spark, sf_dir, "VALS", cat), baseline.table_retrieval(cat, t=4), [4], 2)
    down, up = found.filter("source_schema < target_schema"), found.filter("source_schema > target_schema")
    return match.symmetric(*[x.select(F.col("column_id").alias("query"), F.col("target_column").alias("target")) for x in (down, up)], how="intersect")


@query(
    f"{_COLHASH}{_column_hash('VALS')}, {_SWEEP}, sug AS (SELECT column_id, target_schema, string_agg(table_id || ' ' || CAST(score AS VARCHAR), ', ' ORDER BY rank) AS suggested FROM simdoc WHERE rank <= 4 GROUP BY ALL)"
    " SELECT g.column_id || '>' || g.target_schema AS query, g.target_column AS target, c.cosine, true AS within, s.suggested FROM got g JOIN cs c USING (column_id, target_schema, target_column) JOIN sug s USING (column_id, target_schema) WHERE g.t = 4 AND g.rank = 1"
)
def explain_matches(spark, sf_dir):
    """Matches with the tables suggested for their query."""
    cat = valued(spark, sf_dir)
    tables = cut(baseline.table_retrieval(cat, t=4))
    found = constrained(column_vectors(spark, sf_dir, "VALS", cat), tables, [4], 1)
    name = F.concat_ws(">", "column_id", "target_schema").alias("query")
    out = match.explain(found.select(name, F.col("target_column").alias("target"), "cosine"), tables.filter("rank <= 4").select(name, "rank", "table_id", F.col("score").alias("p")))
    return out.select("query", "target", "cosine", "within", F.array_join(F.transform("suggested", lambda s: F.concat(s["table_id"], F.lit(" "), s["p"].cast("string"))), ", ").alias("suggested"))


def serialization_rows(spark, sf_dir) -> DataFrame:
    cat, truth, out = valued(spark, sf_dir), directed_truth(spark), None
    how = {"query": "column_id", "item": "target_column", "by": ["source_schema", "target_schema"]}
    for kind in serialize.KINDS:
        found = full_search(column_vectors(spark, sf_dir, kind, cat), 20)
        rows = metrics.recall_at(found, truth, K_GRID, cutoff="k", **how).join(metrics.map_at(found, truth, K_GRID, **how), ["source_schema", "target_schema", "k"]).withColumn("kind", F.lit(kind))
        out = rows if out is None else out.union(rows)
    return out


_STUDY = " UNION ALL ".join(
    f"SELECT '{k}' AS kind, source_schema, target_schema, column_id, target_column, row_number() OVER (PARTITION BY column_id, target_schema ORDER BY cosine DESC, target_column) AS rank FROM cs_{k}" for k in serialize.KINDS
)
_STUDY_HASH = ", ".join(_column_hash(k, f"_{k}") for k in serialize.KINDS)


@query(
    f"{_COLHASH}{_STUDY_HASH}, got AS ({_STUDY}), rel AS (SELECT source_schema, target_schema, column_id, count(*) AS n FROM truth GROUP BY ALL),"
    " h AS (SELECT g.*, row_number() OVER (PARTITION BY g.kind, g.column_id, g.target_schema ORDER BY rank) AS hits FROM got g JOIN truth m ON m.column_id = g.column_id AND m.target_schema = g.target_schema AND m.target_column = g.target_column WHERE rank <= 20),"
    f" ap AS (SELECT x.kind, r.source_schema, r.target_schema, r.column_id, r.n, k.k, coalesce(sum(CASE WHEN h.rank <= k.k THEN h.hits / h.rank END), 0) AS s, count(CASE WHEN h.rank <= k.k THEN 1 END) AS c FROM rel r CROSS JOIN (VALUES ('META'), ('VALS'), ('NOTAB'), ('REF')) AS x(kind) CROSS JOIN {_KS} LEFT JOIN h ON h.kind = x.kind AND h.column_id = r.column_id AND h.target_schema = r.target_schema GROUP BY ALL),"
    " per AS (SELECT kind, k, round(sum(c) / sum(n), 6) AS recall, round(avg(s / least(n, k)), 6) AS map FROM ap GROUP BY kind, k, source_schema, target_schema)"
    " SELECT kind, k::INT AS k, round(avg(recall), 5) AS recall, round(avg(map), 5) AS map, round(stddev_samp(recall), 5) AS recall_std, round(stddev_samp(map), 5) AS map_std FROM per GROUP BY kind, k"
)
def serialization_study(spark, sf_dir):
    return serialization_rows(spark, sf_dir).groupBy("kind", "k").agg(F.round(F.avg("recall"), 5).alias("recall"), F.round(F.avg("map"), 5).alias("map"), F.round(F.stddev_samp("recall"), 5).alias("recall_std"), F.round(F.stddev_samp("map"), 5).alias("map_std"))


def _pair_cosine(vecs: DataFrame, wanted: list[tuple[str, str]], kind: str) -> DataFrame:
    """The cosines of named pairs of columns."""
    pairs = F.broadcast(vecs.sparkSession.createDataFrame(wanted, "left string, right string"))
    rows = pairs.join(vecs.select(F.col("column_id").alias("left"), F.col("x").alias("a")), "left").join(vecs.select(F.col("column_id").alias("right"), F.col("x").alias("b")), "right")
    return rows.select(F.concat_ws("~", "left", "right").alias("pair"), F.lit(kind).alias("kind"), (F.round(vectors.cosine(F.col("a"), F.col("b")), 6) + 0.0).alias("cosine"))


def _cosine_sql(wanted, kinds):
    cond = " OR ".join(f"(column_id = '{a}' AND target_column = '{b}')" for a, b in wanted)
    return f"{_COLHASH}{_STUDY_HASH} " + " UNION ALL ".join(f"SELECT column_id || '~' || target_column AS pair, '{k}' AS kind, cosine FROM cs_{k} WHERE {cond}" for k in kinds)


LOOKALIKE = [("dealer.offices.office_name", "star.supplier.s_name"), ("dealer.offices.office_name", "desk.branches.branch_name"), ("desk.branches.branch_name", "star.supplier.s_name")]
SHIFT = [("desk.goods.good_title", "star.part.p_name"), ("dealer.products.product_label", "star.part.p_name"), ("rental.titles.title_name", "star.part.p_name"), ("desk.clients.full_name", "star.customer.c_name")]


@query(_cosine_sql(LOOKALIKE, ("META", "REF")))
def lookalike_tables(spark, sf_dir):
    cat = valued(spark, sf_dir)
    return _pair_cosine(column_vectors(spark, sf_dir, "META", cat), LOOKALIKE, "META").union(_pair_cosine(column_vectors(spark, sf_dir, "REF", cat), LOOKALIKE, "REF"))


@query(_cosine_sql(SHIFT, ("META", "VALS")))
def value_shift(spark, sf_dir):
    cat = valued(spark, sf_dir)
    return _pair_cosine(column_vectors(spark, sf_dir, "META", cat), SHIFT, "META").union(_pair_cosine(column_vectors(spark, sf_dir, "VALS", cat), SHIFT, "VALS"))


_TEXTS = "b AS (SELECT item_id, text FROM benchmark), d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents)"


@query(f"WITH {_TEXTS}, {sql.buckets('b', 'item_id', 256, 'bh')}, {sql.buckets('d', 'doc_id', 256, 'dh')} SELECT * FROM (SELECT item_id, doc_id, score, row_number() OVER (PARTITION BY item_id ORDER BY score DESC, doc_id)::INT AS rank FROM (SELECT item_id, doc_id, {sql.cosine('s')} AS score FROM b CROSS JOIN d LEFT JOIN (SELECT item_id, doc_id, sum(x.value * y.value) AS s FROM bh x JOIN dh y ON x.bucket = y.bucket GROUP BY ALL) USING (item_id, doc_id))) WHERE rank <= 5")
def text_retrieval(spark, sf_dir):
    """The five documents nearest to each benchmark passage; passages are a stated query set, whole texts."""
    b = encode.word_vectors(spark.read.parquet(f"{sf_dir}/benchmark.parquet"), ["item_id"], "text", 256).withColumnRenamed("item_id", "query")
    d = encode.word_vectors(spark.read.parquet(f"{sf_dir}/documents.parquet"), ["doc_id"], "text", 256).withColumnRenamed("doc_id", "neighbour")
    return block.knn(b, d, 5, metric="cosine").select(F.col("query").alias("item_id"), F.col("neighbour").alias("doc_id"), F.col("dist").alias("score"), "rank")
