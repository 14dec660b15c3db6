"""General operators over the given tables, each with its SQL twin."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..functions.vectors import dot, norm, vector_mean, vector_sum
from ..operators import joins
from ..sources import io
from . import query, sql


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def r(col, digits: int = 2):
    return F.round(col, digits)


def money(col):
    """Exact sums: cents as decimals."""
    return F.round(F.sum(F.col(col).cast("decimal(18,2)")).cast("double"), 2)


_MONEY = "round(sum({}::DECIMAL(18,2))::DOUBLE, 2)"

# ---- scans, sources, sinks

_COUNT = " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())


@query(_COUNT)
def scan_parquet(spark, sf_dir):
    out = None
    for name in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        rows = t(spark, sf_dir, name).agg(F.count("*").alias("n")).select(F.lit(name).alias("name"), "n")
        out = rows if out is None else out.union(rows)
    return out


@query("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def scan_pruned(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").filter("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_quantity")


@query(" UNION ALL ".join(f"SELECT '{f}' AS format, count(*) AS n, sum(c_custkey)::BIGINT AS keys, {_MONEY.format('c_acctbal')} AS balance FROM customer" for f in ("csv", "json", "orc")))
def scan_csv_json_orc(spark, sf_dir):
    src, out = t(spark, sf_dir, "customer"), None
    for fmt in ("csv", "json", "orc"):
        back = io.round_trip(src, fmt).agg(F.count("*").alias("n"), F.sum("c_custkey").alias("keys"), money("c_acctbal").alias("balance")).select(F.lit(fmt).alias("format"), "n", "keys", "balance")
        out = back if out is None else out.union(back)
    return out


@query("SELECT year(o_orderdate)::INT AS y, count(*) AS n FROM orders WHERE year(o_orderdate) >= 1996 GROUP BY 1")
def scan_partitioned(spark, sf_dir):
    rows = io.round_trip(t(spark, sf_dir, "orders").withColumn("y", F.year("o_orderdate")), "parquet", partition_by=["y"])
    return rows.filter("y >= 1996").groupBy("y").count().withColumnRenamed("count", "n")


@query("SELECT 'nation' AS table_id, column_name FROM (VALUES ('n_nationkey'), ('n_name'), ('n_regionkey')) AS v(column_name) UNION ALL SELECT 'region', column_name FROM (VALUES ('r_regionkey'), ('r_name')) AS v(column_name)")
def catalog_footer(spark, sf_dir):
    from ..sources.catalog import from_footers

    return from_footers(spark, "given", {n: f"{sf_dir}/{n}.parquet" for n in ("nation", "region")}).columns.select("table_id", "column_name")


@query(f"WITH {sql.found_cte()} SELECT table_id, column_name, is_pk, fk_table AS refers_to FROM cols")
def catalog_ddl(spark, sf_dir):
    """The statements for tables whose keys and references are found in their rows, parsed."""
    from ..sources.catalog import from_ddl, to_ddl
    from .methods import found

    return from_ddl(spark, "ddl", to_ddl(found(spark, sf_dir))).columns.select("table_id", "column_name", "is_pk", F.when(F.size("fk_refs") > 0, F.col("fk_refs")[0]["table"]).alias("refers_to"))


@query(f"WITH {sql.found_cte()} SELECT table_id, column_name, ordinal, dtype, is_pk FROM cols")
def catalog_source(spark, sf_dir):
    """The columns of tables whose keys are found in their rows, as a data source with a partition per table."""
    from .methods import found

    spark.dataSource.register(io.CatalogSource)
    rows = found(spark, sf_dir).columns.select(io.CatalogSource.COLUMNS).collect()  # a row for each column
    return spark.read.format("scenario_catalog").option("columns", json.dumps([list(r) for r in rows])).load().select("table_id", "column_name", "ordinal", "dtype", "is_pk")


@query("SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1")
def bucketed_write(spark, sf_dir):
    """A bucketed table: aggregations and joins on its key need no exchange."""
    name = f"bucketed_{uuid.uuid4().hex[:12]}"
    io.bucketed(t(spark, sf_dir, "customer"), name, 4, "c_mktsegment")
    return spark.table(name).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus AS status, count(*) AS n FROM orders GROUP BY 1")
def sink_partitioned(spark, sf_dir):
    return io.round_trip(t(spark, sf_dir, "orders").withColumn("status", F.col("o_orderstatus")), "parquet", partition_by=["status"]).groupBy("status").agg(F.count("*").alias("n"))


# ---- projection and predicates


@query("SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, CAST(l_quantity AS INT) AS q FROM lineitem")
def proj_exprs(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", r(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.col("l_quantity").cast("int").alias("q"))


@query("SELECT p_partkey AS id, p_name, p_brand AS brand, p_size FROM part")
def proj_star_except(spark, sf_dir):
    return t(spark, sf_dir, "part").drop("p_type", "p_retailprice").withColumnsRenamed({"p_partkey": "id", "p_brand": "brand"})


@query("SELECT o_orderkey FROM orders WHERE (o_orderkey % 4 = 1 AND o_totalprice > 1000) OR NOT (o_orderstatus <> 'F')")
def filter_cmp(spark, sf_dir):
    return t(spark, sf_dir, "orders").filter(((F.col("o_orderkey") % 4 == 1) & (F.col("o_totalprice") > 1000)) | ~(F.col("o_orderstatus") != "F")).select("o_orderkey")


@query("SELECT n_nationkey, n_name FROM nation WHERE n_regionkey IN (SELECT r_regionkey FROM region WHERE r_name IN ('ASIA', 'EUROPE'))")
def filter_in(spark, sf_dir):
    regions = t(spark, sf_dir, "region").filter(F.col("r_name").isin("ASIA", "EUROPE"))
    return t(spark, sf_dir, "nation").join(regions, F.col("n_regionkey") == F.col("r_regionkey"), "left_semi").select("n_nationkey", "n_name")


@query("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_shipdate BETWEEN TIMESTAMP '1995-01-01' AND TIMESTAMP '1996-06-30'")
def filter_between(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").filter("l_quantity between 10 and 12 and l_shipdate between timestamp_ntz '1995-01-01' and timestamp_ntz '1996-06-30'").select("l_orderkey", "l_quantity")


@query("SELECT p_partkey FROM part WHERE p_name LIKE '%a%' AND lower(p_type) LIKE '%e%' AND regexp_matches(p_brand, '[1-3]$')")
def filter_like_rlike(spark, sf_dir):
    return t(spark, sf_dir, "part").filter(F.col("p_name").like("%a%") & F.col("p_type").ilike("%E%") & F.col("p_brand").rlike("[1-3]$")).select("p_partkey")


_LEFT = "(SELECT o_orderkey, o_orderstatus, s FROM orders LEFT JOIN (SELECT l_orderkey AS k, max(l_returnflag) AS s FROM lineitem GROUP BY 1) ON k = o_orderkey)"


def _left(spark, sf_dir):
    lines = t(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.max("l_returnflag").alias("s"))
    return t(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").join(lines, "o_orderkey", "left")


@query(f"SELECT o_orderkey FROM {_LEFT} WHERE s IS NOT DISTINCT FROM NULL OR s IS NOT DISTINCT FROM 'R'")
def filter_null_safe(spark, sf_dir):
    return _left(spark, sf_dir).filter(F.col("s").eqNullSafe(None) | F.col("s").eqNullSafe("R")).select("o_orderkey")


@query(f"SELECT o_orderkey FROM {_LEFT} WHERE s IS NULL")
def filter_isnull(spark, sf_dir):
    return _left(spark, sf_dir).filter(F.col("s").isNull()).select("o_orderkey")


@query("SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")
def case_when(spark, sf_dir):
    p = F.col("o_totalprice")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.when(p > 200000, "high").when(p > 100000, "mid").otherwise("low").alias("band"))


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def filter_exists(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def filter_not_exists(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("o_custkey") == F.col("c_custkey"), "left_anti").select("c_custkey")


@query("SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
def distinct_rows(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus").distinct()


# ---- joins


@query(f"SELECT c_mktsegment, count(*) AS n, {_MONEY.format('o_totalprice')} AS total FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_view_path2(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), money("o_totalprice").alias("total"))


def _path4(spark, sf_dir):
    small = F.broadcast(t(spark, sf_dir, "nation"))  # 25 rows at any scale
    return t(spark, sf_dir, "lineitem").join(t(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(small, F.col("c_nationkey") == F.col("n_nationkey"))


@query("SELECT n_name, count(*) AS n FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def join_view_path3(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query(f"SELECT n_name, count(*) AS n, {_MONEY.format('l_extendedprice')} AS amount FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def join_view_path4(spark, sf_dir):
    return _path4(spark, sf_dir).groupBy("n_name").agg(F.count("*").alias("n"), money("l_extendedprice").alias("amount"))


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left_outer(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a.d, b.d) AS d, coalesce(x, 0) AS orders, coalesce(y, 0) AS events FROM (SELECT o_orderdate::DATE AS d, count(*) AS x FROM orders GROUP BY 1) a FULL JOIN (SELECT ts::DATE AS d, count(*) AS y FROM events GROUP BY 1) b ON a.d = b.d")
def join_full_outer(spark, sf_dir):
    a = t(spark, sf_dir, "orders").groupBy(F.to_date("o_orderdate").alias("d")).agg(F.count("*").alias("x"))
    b = t(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("d")).agg(F.count("*").alias("y"))
    return a.join(b, "d", "full").select("d", F.coalesce("x", F.lit(0)).alias("orders"), F.coalesce("y", F.lit(0)).alias("events"))


@query("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity >= 49)")
def join_semi(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "lineitem").filter("l_quantity >= 49"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@query("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


_LO = "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
for _name, _hint in (("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash"), ("join_default", None)):
    query(_LO, _name)(lambda spark, sf_dir, h=_hint: t(spark, sf_dir, "lineitem").join(t(spark, sf_dir, "orders").hint(h) if h else t(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n")))


@query("SELECT s_name, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")
def join_broadcast(spark, sf_dir):
    return t(spark, sf_dir, "supplier").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_name", "n_name")


@query("SELECT r_name, k.k::INT AS k FROM region CROSS JOIN (VALUES (1), (2), (3), (5), (10), (20)) AS k(k)")
def join_cross(spark, sf_dir):
    return t(spark, sf_dir, "region").select("r_name", F.explode(F.array(*map(F.lit, [1, 2, 3, 5, 10, 20]))).alias("k"))


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_theta(spark, sf_dir):
    a, b = t(spark, sf_dir, "nation").alias("a"), t(spark, sf_dir, "nation").alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"))


_BANDS = [("cheap", 0.0, 1000.0), ("fair", 1000.0, 1500.0), ("dear", 1500.0, 100000.0)]


@query(f"SELECT b.name, count(*) AS n FROM part JOIN (VALUES {', '.join(map(str, _BANDS))}) AS b(name, lo, hi) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY 1")
def join_range(spark, sf_dir):
    bands = spark.createDataFrame(_BANDS, "name string, lo double, hi double")
    return joins.range_join(t(spark, sf_dir, "part").select("p_partkey", "p_retailprice"), bands, "p_retailprice", "lo", "hi", width=250.0).groupBy("name").agg(F.count("*").alias("n"))


@query("SELECT e.event_id, (SELECT max(o_orderdate) FROM orders WHERE o_custkey = e.user_id AND o_orderdate <= e.ts) AS at FROM events e")
def join_asof(spark, sf_dir):
    left = t(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("k"), "ts")
    right = t(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.col("o_orderdate").alias("at"))
    return joins.as_of(left, right, "k", "ts", ["at"]).select("event_id", "at")


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def join_interval(spark, sf_dir):
    a, b = t(spark, sf_dir, "events").alias("a"), t(spark, sf_dir, "events").alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("interval 30 minutes"))
    return a.join(b, on).select(F.col("a.event_id").alias("first"), F.col("b.event_id").alias("second"))


@query("SELECT a.c_custkey AS a, b.c_custkey AS b FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment AND a.c_custkey < b.c_custkey")
def join_self(spark, sf_dir):
    return joins.pairs(t(spark, sf_dir, "customer"), ["c_nationkey", "c_mktsegment"], "c_custkey")


@query("SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_skew_salted(spark, sf_dir):
    return joins.salted(t(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("k")), t(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), "p_brand"), "k", 4).groupBy("p_brand").agg(F.count("*").alias("n"))


# ---- aggregation


@query(f"SELECT l_returnflag, count(*) AS n, {_MONEY.format('l_extendedprice')} AS total, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 4) AS mean FROM lineitem GROUP BY 1")
def agg_hash(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), money("l_extendedprice").alias("total"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), r(F.avg("l_quantity"), 4).alias("mean"))


@query("SELECT o_custkey, array_to_string(list_sort(list(o_orderkey::VARCHAR)), ',') AS orders FROM orders GROUP BY 1")
def agg_sort(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list(F.col("o_orderkey").cast("string"))), ",").alias("orders"))


@query("SELECT l_shipdate::DATE AS day, sum(l_quantity) AS q FROM lineitem GROUP BY 1")
def agg_partial_final(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy(F.to_date("l_shipdate").alias("day")).agg(F.sum("l_quantity").alias("q"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"))


@query("SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_orderkey) AS orders FROM lineitem")
def agg_multi_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_orderkey").alias("orders"))


@query("SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_totalprice > 100000) AS big FROM orders GROUP BY 1")
def agg_filter_clause(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_totalprice") > 100000).alias("big"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def agg_grouping_sets(spark, sf_dir):
    rows = t(spark, sf_dir, "lineitem")
    return rows.groupingSets([[rows.l_returnflag, rows.l_linestatus], [rows.l_returnflag], []], rows.l_returnflag, rows.l_linestatus).agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, sf_dir):
    return t(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))


@query("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, sf_dir):
    rows = t(spark, sf_dir, "customer").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().fillna(0)


@query("SELECT c_custkey, 'c_name' AS col, c_name AS val FROM customer UNION ALL SELECT c_custkey, 'c_mktsegment', c_mktsegment FROM customer")
def agg_unpivot(spark, sf_dir):
    return t(spark, sf_dir, "customer").unpivot("c_custkey", ["c_name", "c_mktsegment"], "col", "val")


@query("SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_samp(l_quantity), 6) AS vr, round(corr(l_quantity, l_discount), 6) AS co, round(covar_samp(l_quantity, l_tax), 6) AS cv FROM lineitem GROUP BY 1")
def agg_stats(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(r(F.stddev_samp("l_quantity"), 6).alias("sd"), r(F.var_samp("l_quantity"), 6).alias("vr"), r(F.corr("l_quantity", "l_discount"), 6).alias("co"), r(F.covar_samp("l_quantity", "l_tax"), 6).alias("cv"))


@query("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.25), 6) AS q1, round(median(l_quantity), 6) AS q2, round(quantile_cont(l_quantity, 0.9), 6) AS q9 FROM lineitem GROUP BY 1")
def agg_percentile(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(r(F.percentile("l_quantity", 0.25), 6).alias("q1"), r(F.median("l_quantity"), 6).alias("q2"), r(F.percentile("l_quantity", 0.9), 6).alias("q9"))


@query("SELECT true AS within FROM range(1)")
def agg_approx(spark, sf_dir):
    """Sketches stay within their error bounds of the exact counts."""
    e = t(spark, sf_dir, "events")
    row = e.agg(F.count_distinct("user_id").alias("x"), F.approx_count_distinct("user_id", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("h"), F.percentile("value", 0.5).alias("m"), F.percentile_approx("value", 0.5, 10000).alias("p"), F.max("value").alias("top"))
    near = lambda a, b, e: F.abs(F.col(a) - F.col(b)) <= e * F.greatest(F.lit(1.0), F.abs(F.col(b)))
    return row.select((near("a", "x", 0.1) & near("h", "x", 0.1) & (F.abs(F.col("p") - F.col("m")) <= 0.02 * F.col("top"))).alias("within"))


@query("SELECT n_regionkey, array_to_string(list_sort(list(DISTINCT n_name)), ',') AS names FROM nation GROUP BY 1")
def agg_collect(spark, sf_dir):
    return t(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names"))


@query("SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS best FROM orders GROUP BY 1")
def agg_max_by(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best"))


@query("SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS least FROM orders GROUP BY 1")
def agg_min_by(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("least"))


@query("SELECT p_brand, arg_max(p_type, (n, p_type)) AS common FROM (SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY ALL) GROUP BY 1")
def agg_mode(spark, sf_dir):
    return t(spark, sf_dir, "part").groupBy("p_brand", "p_type").count().groupBy("p_brand").agg(F.max_by("p_type", F.struct("count", "p_type")).alias("common"))


@query("SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 10")
def agg_having(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).filter("n > 10")


@query("SELECT l_orderkey, bool_and(l_quantity > 5) AS every_one, bool_or(l_quantity > 45) AS any_one FROM lineitem GROUP BY 1")
def agg_bool(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.bool_and(F.col("l_quantity") > 5).alias("every_one"), F.bool_or(F.col("l_quantity") > 45).alias("any_one"))


@query("SELECT label, pos::INT AS pos, round(avg(v), 6) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) GROUP BY label, pos")
def agg_vector(spark, sf_dir):
    return vector_mean(t(spark, sf_dir, "embeddings"), ["label"], "embedding", "x").select("label", F.posexplode("x").alias("pos", "m")).withColumn("m", r("m", 6))


# ---- windows

_O = "PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"


def _o():
    return W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@query(f"SELECT o_orderkey, row_number() OVER ({_O})::INT AS rn FROM orders")
def win_row_number(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(_o()).alias("rn"))


@query("SELECT l_orderkey, l_linenumber, l_quantity, rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity)::INT AS r, dense_rank() OVER (PARTITION BY l_returnflag ORDER BY l_quantity)::INT AS d FROM lineitem")
def win_rank_dense_rank(spark, sf_dir):
    w = W.partitionBy("l_returnflag").orderBy("l_quantity")
    return t(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"))


@query("SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 6) AS p, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 6) AS c FROM part")
def win_percent_rank_cume_dist(spark, sf_dir):
    w = W.partitionBy("p_brand").orderBy("p_retailprice")
    return t(spark, sf_dir, "part").select("p_partkey", r(F.percent_rank().over(w), 6).alias("p"), r(F.cume_dist().over(w), 6).alias("c"))


@query("SELECT c_custkey, ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)::INT AS q FROM customer")
def win_ntile(spark, sf_dir):
    return t(spark, sf_dir, "customer").select("c_custkey", F.ntile(4).over(W.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")).alias("q"))


_E = "PARTITION BY user_id ORDER BY ts, event_id"


def _e():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


@query(f"SELECT event_id, lag(event_type) OVER ({_E}) AS before, lead(event_type) OVER ({_E}) AS after FROM events")
def win_lag_lead(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_type").over(_e()).alias("before"), F.lead("event_type").over(_e()).alias("after"))


@query(f"SELECT event_id, first_value(event_type) OVER ({_E} ROWS UNBOUNDED PRECEDING) AS f, nth_value(event_type, 2) OVER ({_E} ROWS UNBOUNDED PRECEDING) AS s, last_value(CASE WHEN value > 50 THEN value END IGNORE NULLS) OVER ({_E} ROWS UNBOUNDED PRECEDING) AS l FROM events")
def win_first_last_nth(spark, sf_dir):
    w = _e().rowsBetween(W.unboundedPreceding, 0)
    return t(spark, sf_dir, "events").select("event_id", F.first("event_type").over(w).alias("f"), F.nth_value("event_type", 2).over(w).alias("s"), F.last(F.when(F.col("value") > 50, F.col("value")), True).over(w).alias("l"))


@query(f"SELECT o_orderkey, round((sum(o_totalprice::DECIMAL(18,2)) OVER ({_O} ROWS UNBOUNDED PRECEDING))::DOUBLE, 2) AS s FROM orders")
def win_running_sum(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", r(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).over(_o().rowsBetween(W.unboundedPreceding, 0)).cast("double")).alias("s"))


@query(f"SELECT event_id, count(*) OVER ({_E} ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS n, max(value) OVER ({_E} ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS m FROM events")
def win_rows_frame(spark, sf_dir):
    w = _e().rowsBetween(-2, 2)
    return t(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("n"), F.max("value").over(w).alias("m"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_frame(spark, sf_dir):
    seconds = F.rint(F.col("ts").cast("timestamp").cast("double")).cast("long")  # to the nearest second, half to even, as the SQL rounds
    return t(spark, sf_dir, "events").withColumn("s", seconds).select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("n"))


@query("SELECT o_orderkey, round(o_totalprice / sum(o_totalprice) OVER (PARTITION BY o_custkey), 6) AS share FROM orders")
def win_unbounded_ratio(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", r(F.col("o_totalprice") / F.sum("o_totalprice").over(W.partitionBy("o_custkey")), 6).alias("share"))


# ---- sorting, limits, top-k, samples


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_orderstatus DESC NULLS LAST, o_totalprice ASC, o_orderkey)::INT AS n FROM orders WHERE o_custkey < 50")
def sort_multi(spark, sf_dir):
    rows = t(spark, sf_dir, "orders").filter("o_custkey < 50")
    return rows.select("o_orderkey", F.row_number().over(W.orderBy(F.col("o_orderstatus").desc_nulls_last(), "o_totalprice", "o_orderkey")).alias("n"))


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 25")
def limit_topn(spark, sf_dir):
    return t(spark, sf_dir, "part").orderBy(F.col("p_retailprice").desc(), "p_partkey").limit(25).select("p_partkey", "p_retailprice")


_TOPK = "SELECT l_returnflag, l_orderkey, l_partkey, l_extendedprice, rank FROM (SELECT *, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, l_orderkey, l_partkey, l_linenumber)::INT AS rank FROM lineitem) WHERE rank <= 10"


def _topk_order():
    return [F.col("l_extendedprice").desc(), "l_orderkey", "l_partkey", "l_linenumber"]


@query(_TOPK)
def topk_per_group(spark, sf_dir):
    rows = t(spark, sf_dir, "lineitem").withColumn("rank", F.row_number().over(W.partitionBy("l_returnflag").orderBy(*_topk_order()))).filter("rank <= 10")
    return rows.select("l_returnflag", "l_orderkey", "l_partkey", "l_extendedprice", "rank")


@query(_TOPK)
def topk_two_phase(spark, sf_dir):
    """Top-k of each shard, then of the shards: a hot group is ranked by many tasks."""
    shard = F.pmod(F.xxhash64("l_orderkey", "l_partkey"), F.lit(8))
    first = t(spark, sf_dir, "lineitem").withColumn("s", shard).withColumn("a", F.row_number().over(W.partitionBy("l_returnflag", "s").orderBy(*_topk_order()))).filter("a <= 10")
    return first.withColumn("rank", F.row_number().over(W.partitionBy("l_returnflag").orderBy(*_topk_order()))).filter("rank <= 10").select("l_returnflag", "l_orderkey", "l_partkey", "l_extendedprice", "rank")


@query("SELECT c_custkey, c_name FROM customer ORDER BY c_custkey LIMIT 20 OFFSET 40")
def offset_page(spark, sf_dir):
    return t(spark, sf_dir, "customer").orderBy("c_custkey").offset(40).limit(20).select("c_custkey", "c_name")


@query("SELECT o_orderkey, o_custkey FROM orders")
def sort_within_partitions(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").sortWithinPartitions("o_custkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey % 10 = 3")
def sample_hash(spark, sf_dir):
    return t(spark, sf_dir, "orders").filter(F.pmod("o_orderkey", F.lit(10)) == 3).select("o_orderkey")


@query("SELECT c_custkey, c_mktsegment FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY md5(c_custkey::VARCHAR), c_custkey) AS rn, count(*) OVER (PARTITION BY c_mktsegment) AS n FROM customer) WHERE rn <= 0.2 * n")
def sample_stratified(spark, sf_dir):
    by = W.partitionBy("c_mktsegment")
    rows = t(spark, sf_dir, "customer").withColumns({"rn": F.row_number().over(by.orderBy(F.md5(F.col("c_custkey").cast("string")), "c_custkey")), "n": F.count("*").over(by)})
    return rows.filter("rn <= 0.2 * n").select("c_custkey", "c_mktsegment")


# ---- sets

_SETS = {"union_all": "UNION ALL", "union": "UNION", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}


def _set(kind: str):
    def run(spark, sf_dir):
        a, b = t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
        return {"union_all": a.unionAll(b), "union": a.union(b).distinct(), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}[kind]

    return run


for _k, _s in _SETS.items():
    query(f"SELECT c_nationkey AS k FROM customer {_s} SELECT s_nationkey FROM supplier", f"set_{_k}")(_set(_k))


@query("SELECT c_custkey AS id, c_name AS name, c_mktsegment AS segment FROM customer UNION ALL SELECT s_suppkey, s_name, NULL FROM supplier")
def union_by_name(spark, sf_dir):
    a = t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), F.col("c_name").alias("name"), F.col("c_mktsegment").alias("segment"))
    return a.unionByName(t(spark, sf_dir, "supplier").select(F.col("s_name").alias("name"), F.col("s_suppkey").alias("id")), allowMissingColumns=True)


# ---- scalar functions


def _scalar(name: str, table: str, key: str, oracle: str, cols):
    """``cols``: made when the query runs, since expressions need a session."""
    query(f"SELECT {key}, {oracle} FROM {table}", name)(lambda spark, sf_dir: t(spark, sf_dir, table).select(key, *cols()))


_scalar("str_case_trim_pad", "part", "p_partkey", "upper(p_name) AS u, trim('  ' || p_brand || ' ') AS tr, lpad(p_partkey::VARCHAR, 8, '0') AS l, rpad(p_brand, 12, '.') AS rp", lambda: [F.upper("p_name").alias("u"), F.trim(F.concat(F.lit("  "), "p_brand", F.lit(" "))).alias("tr"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("l"), F.rpad("p_brand", 12, ".").alias("rp")])
_scalar("str_split_tokens", "part", "p_partkey", "array_to_string(string_split(lower(regexp_replace(regexp_replace(p_type, '([a-z])([A-Z])', '\\1 \\2', 'g'), '[_# ]+', ' ', 'g')), ' '), '|') AS words", lambda: [F.array_join(F.split(F.lower(F.regexp_replace(F.regexp_replace("p_type", "([a-z])([A-Z])", "$1 $2"), "[_# ]+", " ")), " "), "|").alias("words")])
_scalar("str_concat_ws", "nation", "n_nationkey", "concat_ws('>', n_name, n_regionkey::VARCHAR, n_nationkey::VARCHAR) AS c", lambda: [F.concat_ws(">", "n_name", F.col("n_regionkey").cast("string"), F.col("n_nationkey").cast("string")).alias("c")])
_scalar("str_regex_extract_replace", "part", "p_partkey", "regexp_extract(p_brand, '([0-9])', 1) AS d, regexp_replace(p_name, '[aeiou]', '*', 'g') AS v", lambda: [F.regexp_extract("p_brand", "([0-9])", 1).alias("d"), F.regexp_replace("p_name", "[aeiou]", "*").alias("v")])
_scalar("str_substr_instr", "customer", "c_custkey", "substr(c_name, 3, 5) AS s, instr(c_name, '0')::INT AS i, length(c_name)::INT AS n", lambda: [F.substring("c_name", 3, 5).alias("s"), F.instr("c_name", "0").alias("i"), F.length("c_name").alias("n")])
_scalar("str_levenshtein", "nation", "n_nationkey", "levenshtein(n_name, 'FRANCE')::INT AS d", lambda: [F.levenshtein("n_name", F.lit("FRANCE")).alias("d")])
_scalar("hash_md5_bucket", "nation", "n_nationkey", "('0x' || substr(md5(n_name), 1, 8))::BIGINT % 64 AS b", lambda: [(F.conv(F.substring(F.md5("n_name"), 1, 8), 16, 10).cast("long") % 64).alias("b")])
_scalar("hash_fold", "customer", "c_custkey", "('0x' || substr(md5(c_custkey::VARCHAR), 1, 8))::BIGINT % 5 AS fold", lambda: [(F.conv(F.substring(F.md5(F.col("c_custkey").cast("string")), 1, 8), 16, 10).cast("long") % 5).alias("fold")])
_scalar("dt_trunc", "orders", "o_orderkey", "date_trunc('month', o_orderdate)::DATE AS m, date_trunc('year', o_orderdate)::DATE AS y", lambda: [F.to_date(F.date_trunc("month", "o_orderdate")).alias("m"), F.to_date(F.date_trunc("year", "o_orderdate")).alias("y")])
_scalar("dt_parts", "orders", "o_orderkey", "year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS d, quarter(o_orderdate)::INT AS q, dayofyear(o_orderdate)::INT AS j", lambda: [F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d"), F.quarter("o_orderdate").alias("q"), F.dayofyear("o_orderdate").alias("j")])
_scalar("dt_diff_add", "orders", "o_orderkey", "datediff('day', o_orderdate::DATE, DATE '1999-01-01')::INT AS n, (o_orderdate::DATE + 30)::DATE AS later", lambda: [F.date_diff(F.lit("1999-01-01").cast("date"), F.to_date("o_orderdate")).alias("n"), F.date_add(F.to_date("o_orderdate"), 30).alias("later")])
_scalar("dt_format_parse", "orders", "o_orderkey", "strftime(o_orderdate, '%Y/%m/%d') AS f, strptime(strftime(o_orderdate, '%Y%m%d'), '%Y%m%d')::DATE AS p", lambda: [F.date_format("o_orderdate", "yyyy/MM/dd").alias("f"), F.to_date(F.date_format("o_orderdate", "yyyyMMdd"), "yyyyMMdd").alias("p")])
_scalar("dt_interval", "orders", "o_orderkey", "(o_orderdate + INTERVAL 3 MONTH)::DATE AS q", lambda: [F.to_date(F.add_months(F.to_date("o_orderdate"), 3)).alias("q")])
_scalar("math_exp_log_pow", "part", "p_partkey", "round(exp(-p_size / 10.0), 6) AS e, round(ln(p_retailprice), 6) AS l, round(pow(p_size, 1.5), 4) AS p", lambda: [r(F.exp(-F.col("p_size") / 10.0), 6).alias("e"), r(F.log("p_retailprice"), 6).alias("l"), r(F.pow("p_size", F.lit(1.5)), 4).alias("p")])
_scalar("math_sigmoid", "customer", "c_custkey", "round(1 / (1 + exp(-c_acctbal / 1000)), 6) AS s", lambda: [r(1 / (1 + F.exp(-F.col("c_acctbal") / 1000)), 6).alias("s")])
_scalar("math_round_floor", "part", "p_partkey", "floor(p_retailprice)::BIGINT AS f, ceil(p_retailprice)::BIGINT AS c, sign(p_retailprice - 1200)::INT AS s", lambda: [F.floor("p_retailprice").alias("f"), F.ceil("p_retailprice").alias("c"), F.signum(F.col("p_retailprice") - 1200).cast("int").alias("s")])
_scalar("math_greatest_least", "orders", "o_orderkey", "greatest(o_orderkey, o_custkey) AS g, least(o_orderkey, o_custkey) AS l", lambda: [F.greatest("o_orderkey", "o_custkey").alias("g"), F.least("o_orderkey", "o_custkey").alias("l")])
_scalar("arr_l2_norm", "embeddings", "vec_id", "round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS n", lambda: [r(norm(F.col("embedding")), 6).alias("n")])
_scalar("arr_zip_with_aggregate", "embeddings", "vec_id", "round(list_dot_product(embedding::DOUBLE[], list_reverse(embedding::DOUBLE[])), 6) AS d", lambda: [r(dot(F.col("embedding"), F.reverse("embedding")), 6).alias("d")])
_scalar("arr_slice_sort_distinct", "embeddings", "vec_id", "array_to_string(list_sort(list_distinct([floor(x * 10)::INT::VARCHAR for x in embedding[1:8]])), ',') AS a", lambda: [F.array_join(F.array_sort(F.array_distinct(F.transform(F.slice("embedding", 1, 8), lambda x: F.floor(x * F.lit(10.0).cast("float")).cast("int").cast("string")))), ",").alias("a")])
_scalar("arr_except_union", "part", "p_partkey", "array_to_string(list_sort(list_distinct(list_filter(string_split(p_name, ' '), lambda x: NOT list_contains(string_split(p_type, ' '), x)))), ',') AS e", lambda: [F.array_join(F.array_sort(F.array_except(F.split("p_name", " "), F.split("p_type", " "))), ",").alias("e")])
_scalar("arr_transform_filter_exists", "embeddings", "vec_id", "len(list_filter(embedding, lambda x: x > 0))::INT AS n, len(list_filter(embedding, lambda x: x > 0.4)) > 0 AS big", lambda: [F.size(F.filter("embedding", lambda x: x > 0)).alias("n"), F.exists("embedding", lambda x: x > F.lit(0.4).cast("float")).alias("big")])
_scalar("arr_sequence_flatten", "nation", "n_nationkey", "array_to_string(flatten([range(0, n_regionkey + 1), range(5, 7)]), ',') AS s", lambda: [F.array_join(F.flatten(F.array(F.sequence(F.lit(0), F.col("n_regionkey")), F.array(F.lit(5), F.lit(6)))), ",").alias("s")])
_scalar("map_build_lookup", "labels", "doc_id", "quality::INT AS q", lambda: [F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array(F.col("quality"), F.col("toxic")))["quality"].alias("q")])
_scalar("struct_nest_unnest", "nation", "n_nationkey", "n_name AS name, n_regionkey AS key", lambda: [F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("key"))["name"].alias("name"), F.struct(F.col("n_regionkey").alias("key"))["key"].alias("key")])
_scalar("json_get", "events", "event_id", "json_extract_string(props, '$.k') AS k", lambda: [F.get_json_object("props", "$.k").alias("k")])
_scalar("json_from_to", "events", "event_id", "json_extract_string(props, '$.k') AS k", lambda: [F.get_json_object(F.to_json(F.from_json("props", "k string")), "$.k").alias("k")])
_scalar("null_coalesce_nvl_nullif", "nation", "n_nationkey", "coalesce(nullif(n_regionkey, 0), -1)::INT AS c, n_regionkey IS NULL AS z", lambda: [F.coalesce(F.nullif("n_regionkey", F.lit(0)), F.lit(-1)).alias("c"), F.col("n_regionkey").isNull().alias("z")])


@query("SELECT l_returnflag, sum(l_extendedprice::DECIMAL(12,2))::DOUBLE AS s FROM lineitem GROUP BY 1")
def math_decimal(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("double").alias("s"))


@query("SELECT p_partkey, pos::INT AS pos, w FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w, generate_subscripts(string_split(p_name, ' '), 1) - 1 AS pos FROM part)")
def arr_explode_posexplode(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "w"))


@query("SELECT n_nationkey, substr(n_name, i::INT, 3) AS g FROM nation, range(1, 30) AS r(i) WHERE i <= length(n_name) - 2")
def str_ngrams(spark, sf_dir):
    return t(spark, sf_dir, "nation").select("n_nationkey", F.explode(F.transform(F.sequence(F.lit(1), F.length("n_name") - 2), lambda i: F.substring("n_name", i, F.lit(3)))).alias("g"))


_CODES = "translate(regexp_replace(upper(n_name), '[^A-Z]', 'A', 'g'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', '01230127022455012623017202')"
for _d in "112233445566":
    _CODES = f"replace({_CODES if _CODES.startswith('replace(replace(') else 'replace(' + _CODES + ", '7', '')"}, '{_d}{_d}', '{_d}')"


@query(f"SELECT n_nationkey, upper(n_name)[1] || rpad(substr(replace(substr(replace({_CODES}, '00', '0'), 2), '0', ''), 1, 3), 3, '0') AS s FROM nation")
def str_soundex(spark, sf_dir):
    return t(spark, sf_dir, "nation").select("n_nationkey", F.soundex("n_name").alias("s"))


@query("SELECT doc_id, k, v FROM (SELECT doc_id, unnest(['quality', 'toxic']) AS k, unnest([quality, toxic]) AS v FROM labels) WHERE v > 0")
def map_entries_filter(spark, sf_dir):
    m = F.map_from_arrays(F.array(F.lit("quality"), F.lit("toxic")), F.array("quality", "toxic"))
    return t(spark, sf_dir, "labels").select("doc_id", F.explode(F.map_filter(m, lambda k, v: v > 0)).alias("k", "v"))


@query("SELECT DISTINCT 'STRUCT<k: BIGINT>' AS s FROM range(1)")
def json_schema_of(spark, sf_dir):
    return spark.range(1).select(F.schema_of_json(F.lit('{"k": 1}')).alias("s"))


# ---- the SQL surface


def _sql(name: str, text: str, oracle: str | None = None):
    def run(spark, sf_dir):
        for n in ("region", "nation", "customer", "orders"):
            t(spark, sf_dir, n).createOrReplaceTempView(n)
        return spark.sql(text)

    query(oracle or text, name)(run)


_sql("sql_cte_recursive", "WITH RECURSIVE e(src, dst) AS (VALUES ('region', 'nation'), ('nation', 'customer'), ('nation', 'supplier'), ('customer', 'orders'), ('orders', 'lineitem')), p(src, dst, n) AS (SELECT src, dst, 1 FROM e UNION ALL SELECT p.src, e.dst, p.n + 1 FROM p JOIN e ON p.dst = e.src WHERE p.n < 5) SELECT src, dst, n FROM p")
_sql("sql_subquery_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
_sql("sql_exists", "SELECT n_nationkey FROM nation WHERE EXISTS (SELECT 1 FROM customer WHERE c_nationkey = n_nationkey AND c_acctbal > 9000)")
_sql("sql_lateral", "SELECT r_name, x.n FROM region, LATERAL (SELECT count(*) AS n FROM nation WHERE n_regionkey = r_regionkey) AS x")
_sql("sql_values", "SELECT a, b FROM (VALUES (1, 'x'), (2, 'y')) AS v(a, b)")


# ---- registered functions


@query("SELECT vec_id, round(list_cosine_similarity(embedding::DOUBLE[], list_reverse(embedding::DOUBLE[])), 5) AS c FROM embeddings")
def udf_cosine(spark, sf_dir):
    from ..functions.registered import register

    register(spark)
    t(spark, sf_dir, "embeddings").createOrReplaceTempView("embeddings")
    return spark.sql("SELECT vec_id, round(cosine_sim(cast(embedding AS array<double>), reverse(cast(embedding AS array<double>))), 5) AS c FROM embeddings")


@query("WITH RECURSIVE e(a, b) AS (VALUES ('region', 'nation'), ('nation', 'customer'), ('customer', 'orders')), p(a, b, path, n) AS (SELECT DISTINCT x, x, x, 1 FROM (SELECT a AS x FROM e UNION SELECT b FROM e) UNION ALL SELECT p.a, e.b, p.path || '>' || e.b, n + 1 FROM p JOIN e ON p.b = e.a WHERE n < 3) SELECT path, n AS n_tables FROM p")
def udtf_shortest_views(spark, sf_dir):
    from ..functions.registered import register

    register(spark)
    return spark.sql("SELECT path, n_tables FROM shortest_views('region>nation,nation>customer,customer>orders', 3)")


@query("SELECT round(sum(0.9 * y * pow(1 - p, 2) * -ln(p) + 0.1 * (1 - y) * pow(p, 2) * -ln(1 - p)), 5) AS focal, round(sum(exp(-0.5::DOUBLE * quality)), 5) AS soft FROM (SELECT ((doc_id * 37) % 100 + 0.5::DOUBLE) / 100 AS p, toxic::DOUBLE AS y, quality FROM labels)")
def udf_focal_soft(spark, sf_dir):
    from ..functions.registered import register

    register(spark)
    t(spark, sf_dir, "labels").createOrReplaceTempView("labels")
    return spark.sql("SELECT round(sum(focal_term(p, y)), 5) AS focal, round(sum(soft_label(quality, 0.5D)), 5) AS soft FROM (SELECT ((doc_id * 37) % 100 + 0.5D) / 100 AS p, cast(toxic AS double) AS y, cast(quality AS double) AS quality FROM labels)")


_BY_LABEL = "SELECT label, pos::INT AS pos, round({}(v), 5) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) GROUP BY label, pos"


def _by_label(spark, sf_dir, name: str):
    from ..functions.registered import register

    register(spark)
    t(spark, sf_dir, "embeddings").createOrReplaceTempView("embeddings")
    return spark.sql(f"SELECT label, pos, round(m, 5) AS m FROM (SELECT label, {name}(embedding) AS x FROM embeddings GROUP BY label) LATERAL VIEW posexplode(x) AS pos, m")


@query(_BY_LABEL.format("sum"))
def udaf_vector_sum(spark, sf_dir):
    return _by_label(spark, sf_dir, "vector_sum")


@query(_BY_LABEL.format("avg"))
def udaf_vector_mean(spark, sf_dir):
    return _by_label(spark, sf_dir, "vector_mean")


@query(_BY_LABEL.format("sum"))
def agg_vector_sum(spark, sf_dir):
    return vector_sum(t(spark, sf_dir, "embeddings"), ["label"], "embedding", "x").select("label", F.posexplode("x").alias("pos", "m")).withColumn("m", r("m", 5))


@query("SELECT user_id, round(sum(h / rk * rel) / sum(rel), 6) AS ap FROM (SELECT user_id, rk, rel, sum(rel) OVER (PARTITION BY user_id ORDER BY rk) AS h FROM (SELECT user_id, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS rk, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE 0 END AS rel FROM events)) GROUP BY 1 HAVING sum(rel) > 0")
def udaf_average_precision(spark, sf_dir):
    from ..functions.registered import average_precision

    rows = t(spark, sf_dir, "events").select("user_id", F.row_number().over(W.partitionBy("user_id").orderBy(F.col("value").desc(), "event_id")).alias("rk"), (F.col("event_type") == "purchase").cast("double").alias("rel"))
    return rows.groupBy("user_id").agg(average_precision("rk", "rel").alias("ap")).filter("ap > 0").select("user_id", r("ap", 6).alias("ap"))
