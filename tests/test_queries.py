"""Registered queries against their SQL twins on the smallest tables, and plan shapes that scale rests on."""

import os

import duckdb
import pytest

from ctxmatch import queries as registry
from ctxmatch.sources.scenarios import GIVEN

SF = "/root/testdata/sf0.001"
registry.load_all()
CHEAP = [k for k in registry.ORACLES if k.split("_")[0] in ("graph", "views", "rac", "labels", "join", "win", "set", "filter", "topk", "arr", "st", "udtf", "udaf") or k in ("simdoc_tables", "recall_at_t", "knn_l2", "vector_recall_map", "mlp_topt", "profile_inclusions", "scan_csv_json_orc", "catalog_source", "agg_cube", "agg_pivot", "agg_percentile")]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for name in GIVEN:
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    return con


def rows_of(names, rows):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple("" if r[i] is None else str(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", CHEAP)
def test_query_equals_its_sql(spark, duck, name):
    df = registry.QUERIES[name](spark, SF)
    relation = duck.sql(registry.ORACLES[name])
    assert sorted(df.columns) == sorted(relation.columns)
    assert rows_of(df.columns, df.collect()) == rows_of(relation.columns, relation.fetchall())


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    pruned = plan(registry.QUERIES["scan_pruned"](spark, SF))
    assert "PushedFilters: [IsNotNull(l_quantity), IsNotNull(l_returnflag), GreaterThan(l_quantity,45.0)" in pruned
    assert "ReadSchema: struct<l_orderkey:bigint,l_quantity:double,l_returnflag:string>" in pruned
    assert "WindowGroupLimit" in plan(registry.QUERIES["topk_per_group"](spark, SF))
    assert "Exchange" not in plan(registry.QUERIES["bucketed_write"](spark, SF))
    two_phase = plan(registry.QUERIES["agg_partial_final"](spark, SF))
    assert "partial_sum" in two_phase
    assert "PartitionFilters: [isnotnull(y" in plan(registry.QUERIES["scan_partitioned"](spark, SF))


def test_entry_points():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(registry.QUERIES) > 200
    assert os.path.exists(os.path.join(os.path.dirname(entry.__file__), "bench.py"))


def _against_sql(spark, name, folder, table):
    """Rows of a query and of its SQL over one table of a folder."""
    con = duckdb.connect()
    con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet'")
    df, relation = registry.QUERIES[name](spark, str(folder)), con.sql(registry.ORACLES[name])
    return rows_of(df.columns, df.collect()), rows_of(relation.columns, relation.fetchall()), df


def test_self_join_meets_in_bins(spark, tmp_path):
    duckdb.sql(f"COPY (SELECT (k * 13) % 401 - 200 AS c_custkey, (k % 2)::INT AS c_nationkey, CASE WHEN k % 7 > 0 THEN 's' || k % 3 END AS c_mktsegment FROM range(420) AS r(k)) TO '{tmp_path}/customer.parquet'")
    got, wanted, df = _against_sql(spark, "join_self", tmp_path, "customer")
    assert got == wanted and len(got) > 500
    assert "_bin" in plan(df)


def test_self_join_keeps_partners_at_any_distance(spark, tmp_path):
    duckdb.sql(f"COPY (SELECT CASE WHEN k % 50 > 0 THEN (k * 7919) % 90001 - 45000 END AS c_custkey, CASE WHEN k % 11 > 0 THEN (k % 2)::INT END AS c_nationkey, 's' || k % 3 AS c_mktsegment FROM (SELECT * FROM range(300) UNION ALL SELECT * FROM range(20)) AS r(k)) TO '{tmp_path}/customer.parquet'")
    got, wanted, _ = _against_sql(spark, "join_self", tmp_path, "customer")
    rows = duckdb.sql(f"SELECT * FROM '{tmp_path}/customer.parquet'").fetchall()
    whole = sorted((str(a), str(b)) for a, *x in rows for b, *y in rows if None not in (a, b, *x) and x == y and a < b)
    assert got == wanted == whole and max(int(b) - int(a) for a, b in got) > 40000


@pytest.mark.parametrize("tile", [1, 7, 2048])
def test_pairs_are_whole_at_any_size_of_bins(spark, tile):
    from ctxmatch.operators import joins

    rows = [(k % 3 if k % 5 else 0, (k * 37) % 101 - 50) for k in range(110)]
    got = joins.pairs(spark.createDataFrame(rows, "g int, v long"), ["g"], "v", tile).collect()
    assert sorted(map(tuple, got)) == sorted((a, b) for g, a in rows for h, b in rows if g == h and a < b)


def test_range_frame_rounds_seconds_as_its_sql(spark, tmp_path):
    duckdb.sql(f"COPY (SELECT k AS event_id, TIMESTAMP '2024-01-01 00:00:00' + to_microseconds(k * 43200250000) AS ts, k % 2 AS user_id FROM range(400) AS r(k)) TO '{tmp_path}/events.parquet'")
    got, wanted, _ = _against_sql(spark, "win_range_frame", tmp_path, "events")
    assert got == wanted


FROM_DATA = ("augmentation_statistics", "catalog_counts", "catalog_ddl", "catalog_source", "catalog_valid_refs", "constraint_text")


@pytest.fixture(scope="module")
def changed(tmp_path_factory):
    """The smallest tables with a customer that occurs twice and a supplier of no nation: one key and one reference less than the given tables have."""
    folder = tmp_path_factory.mktemp("changed")
    for name in GIVEN:
        more = {"customer": f" UNION ALL SELECT * FROM '{SF}/customer.parquet' WHERE c_custkey = 3", "supplier": f" UNION ALL SELECT * REPLACE (s_suppkey + 5000 AS s_suppkey, -1 AS s_nationkey) FROM '{SF}/supplier.parquet' WHERE s_suppkey = 1"}.get(name, "")
        duckdb.sql(f"COPY (SELECT * FROM '{SF}/{name}.parquet'{more}) TO '{folder}/{name}.parquet'")
    return folder


@pytest.mark.parametrize("name", FROM_DATA)
def test_catalogs_follow_the_given_tables(spark, changed, name):
    seen = []
    for folder in (SF, changed):
        con = duckdb.connect()
        for table in GIVEN:
            con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet'")
        df, relation = registry.QUERIES[name](spark, str(folder)), con.sql(registry.ORACLES[name])
        seen.append(rows_of(df.columns, df.collect()))
        assert sorted(df.columns) == sorted(relation.columns) and seen[-1] == rows_of(relation.columns, relation.fetchall())
    assert seen[0] != seen[1]


def test_references_found_in_rows(spark):
    from ctxmatch.queries.methods import found

    refs = {(r.weak_column, r.strong_column) for r in found(spark, SF).refs.collect()}
    assert {("n_regionkey", "r_regionkey"), ("c_nationkey", "n_nationkey"), ("o_custkey", "c_custkey")} <= refs


def test_statements_are_parsed(spark):
    from ctxmatch.sources.catalog import from_ddl

    ddl = "CREATE TABLE nation (n_nationkey int, n_name varchar(25), n_regionkey int, PRIMARY KEY (n_nationkey), FOREIGN KEY (n_regionkey) REFERENCES region (r_regionkey));\nCREATE TABLE region (r_regionkey int PRIMARY KEY, area decimal(12,2));"
    cat = from_ddl(spark, "ddl", ddl)
    assert {(r.table_id, r.column_name, r.dtype, r.is_pk) for r in cat.columns.collect()} == {("nation", "n_nationkey", "int", True), ("nation", "n_name", "varchar(25)", False), ("nation", "n_regionkey", "int", False), ("region", "r_regionkey", "int", True), ("region", "area", "decimal(12,2)", False)}
    assert [tuple(r) for r in cat.refs.collect()] == [("ddl", "region", "r_regionkey", "nation", "n_regionkey")]


def test_word_hashes_of_conversations(spark, duck):
    df, relation = registry.QUERIES["encode_wordhash"](spark, SF), duck.sql(registry.ORACLES["encode_wordhash"])
    assert rows_of(df.columns, df.collect()) == rows_of(relation.columns, relation.fetchall())
    assert "conversations.parquet" in plan(df)
