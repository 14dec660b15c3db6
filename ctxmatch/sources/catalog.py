"""Catalogs: metadata of tables, columns and references as DataFrames."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import profile
from .scenarios import Schema, columns_of, derived_sql, order_of

COLUMNS = "schema_id string, table_id string, column_id string, column_name string, ordinal int, dtype string, is_pk boolean, fk_refs array<struct<table:string,column:string>>, values array<string>"
REFS = "schema_id string, strong_table string, strong_column string, weak_table string, weak_column string"


@dataclass
class Catalog:
    tables: DataFrame  # schema_id, table_id, table_name, n_cols
    columns: DataFrame  # COLUMNS
    refs: DataFrame  # REFS


def load(spark: SparkSession, schemas: list[Schema]) -> Catalog:
    """A catalog from parsed schemas; ``validate`` has been applied."""
    cols = [(s.name, t, f"{s.name}.{t}.{c}", c, o, d, pk, [ref] if ref else [], []) for s in schemas for t, c, o, d, pk, ref, _ in s.columns]
    refs = [(s.name, *r) for s in schemas for r in s.refs]
    return validate(from_rows(spark.createDataFrame(cols, COLUMNS), spark.createDataFrame(refs, REFS)))


def from_rows(columns: DataFrame, refs: DataFrame) -> Catalog:
    tables = columns.groupBy("schema_id", "table_id").agg(F.count("*").cast("int").alias("n_cols")).select("schema_id", "table_id", F.col("table_id").alias("table_name"), "n_cols")
    return Catalog(tables, columns, refs)


def validate(cat: Catalog) -> Catalog:
    """Without self references, repeated references and references to columns that do not exist."""
    known = cat.columns.select("schema_id", F.col("table_id").alias("t"), F.col("column_name").alias("c"))
    refs = cat.refs.filter("strong_table <> weak_table").dropDuplicates()
    for side in ("strong", "weak"):
        there = known.withColumnsRenamed({"t": f"{side}_table", "c": f"{side}_column"})
        refs = refs.join(there, ["schema_id", f"{side}_table", f"{side}_column"], "left_semi")
    return Catalog(cat.tables, cat.columns, refs.select("schema_id", "strong_table", "strong_column", "weak_table", "weak_column"))


def from_footers(spark: SparkSession, schema_id: str, paths: dict[str, str]) -> Catalog:
    """Columns from the schemas of files (only footers are read); keys and references are left to profiling."""
    rows = [(schema_id, t, f"{schema_id}.{t}.{f.name}", f.name, k, f.dataType.simpleString(), False, [], []) for t, p in paths.items() for k, f in enumerate(spark.read.parquet(p).schema, 1)]
    return from_rows(spark.createDataFrame(rows, COLUMNS), spark.createDataFrame([], REFS))


def from_data(spark: SparkSession, schema_id: str, tables: dict[str, DataFrame]) -> Catalog:
    """A catalog whose keys and references are found in the rows: a key is a whole-numbered column without nulls and repeated values; every other one refers to the key
    with the fewest values (then by name) that holds all of its values, if there is one. The driver reads a row for each whole-numbered column.
    """
    whole = {t: df.select([c for c, kind in df.dtypes if kind in ("int", "bigint")]) for t, df in tables.items()}
    counts = reduce(DataFrame.union, [profile.unique_counts(df, t) for t, df in whole.items()]).filter("is_key").collect()
    keys = {(r.table_id, r.column_name): r.n_distinct for r in counts}
    found = profile.references(whole, list(keys)) if keys else spark.createDataFrame([], profile.REFERENCES)
    sizes = spark.createDataFrame([(*k, n) for k, n in keys.items()], "strong_table string, strong_column string, n long")
    own = sizes.select(F.col("strong_table").alias("weak_table"), F.col("strong_column").alias("weak_column"))
    found = found.join(F.broadcast(own), ["weak_table", "weak_column"], "left_anti").join(F.broadcast(sizes), ["strong_table", "strong_column"])
    least = found.groupBy("weak_table", "weak_column").agg(F.min(F.struct("n", "strong_table", "strong_column")).alias("s"))
    refs = least.select(F.lit(schema_id).alias("schema_id"), "s.strong_table", "s.strong_column", "weak_table", "weak_column")
    rows = [(schema_id, t, f"{schema_id}.{t}.{f.name}", f.name, k, f.dataType.simpleString().removesuffix("_ntz"), (t, f.name) in keys) for t, df in tables.items() for k, f in enumerate(df.schema, 1)]
    named = spark.createDataFrame(rows, "schema_id string, table_id string, column_id string, column_name string, ordinal int, dtype string, is_pk boolean")
    to = refs.select(F.col("weak_table").alias("table_id"), F.col("weak_column").alias("column_name"), F.array(F.struct(F.col("strong_table").alias("table"), F.col("strong_column").alias("column"))).alias("fk_refs"))
    columns = named.join(to, ["table_id", "column_name"], "left").withColumn("fk_refs", F.coalesce("fk_refs", F.array().cast("array<struct<table:string,column:string>>"))).withColumn("values", F.array().cast("array<string>"))
    return validate(from_rows(columns.select(*named.columns, "fk_refs", "values"), refs))


def to_ddl(cat: Catalog) -> str:
    """CREATE TABLE statements of a catalog, which the driver reads: a row for each column."""
    out: dict[str, list[str]] = {}
    last: dict[str, list[str]] = {}
    for r in cat.columns.orderBy("table_id", "ordinal").collect():
        out.setdefault(r.table_id, []).append(f"{r.column_name} {r.dtype}")
        last.setdefault(r.table_id, []).extend([f"PRIMARY KEY ({r.column_name})"] * r.is_pk + [f"FOREIGN KEY ({r.column_name}) REFERENCES {x['table']} ({x['column']})" for x in r.fk_refs])
    return "\n".join(f"CREATE TABLE {t} ({', '.join(parts + last[t])});" for t, parts in out.items())


def from_jdbc(spark: SparkSession, url: str, schema_id: str, **options: str) -> DataFrame:
    """table, column, ordinal and type rows of a database's information schema."""
    query = f"SELECT table_name, column_name, ordinal_position, data_type FROM information_schema.columns WHERE table_schema = '{schema_id}'"
    return spark.read.format("jdbc").options(url=url, query=query, **options).load()


def from_ddl(spark: SparkSession, schema_id: str, ddl: str) -> Catalog:
    """A catalog from CREATE TABLE statements with PRIMARY KEY and FOREIGN KEY ... REFERENCES clauses."""
    schema = Schema(schema_id)
    for table, body in re.findall(r"create\s+table\s+(\w+)\s*\((.*?)\)\s*;", ddl, re.I | re.S):
        parts = [p.strip() for p in re.split(r",(?![^()]*\))", body)]
        keys = {k.strip() for p in parts if (m := re.match(r"primary\s+key\s*\((.*?)\)", p, re.I)) for k in m[1].split(",")}
        refs = {m[1]: (m[2], m[3]) for p in parts if (m := re.match(r"foreign\s+key\s*\(\s*(\w+)\s*\)\s*references\s+(\w+)\s*\(\s*(\w+)\s*\)", p, re.I))}
        plain = [p for p in parts if not re.match(r"(primary|foreign)\s+key", p, re.I)]
        schema.tables[table] = table
        for ordinal, p in enumerate(plain, 1):
            name, dtype, *_ = p.split()
            schema.columns.append((table, name, ordinal, dtype.lower(), name in keys or bool(re.search(r"primary\s+key", p, re.I)), refs.get(name), ""))
        schema.refs += [(t, c, table, col) for col, (t, c) in refs.items()]
    return load(spark, [schema])


def shown(col, dtype: str):
    """A value as text: two decimals, days of timestamps; of long texts the tokens that a sentence can hold at most."""
    if dtype == "double":
        return F.format_string("%.2f", col)
    if dtype == "timestamp":
        return F.date_format(col, "yyyy-MM-dd")
    if dtype == "array<float>":
        return F.array_join(F.transform(F.slice(col, 1, 3), lambda x: F.format_string("%.2f", x.cast("double"))), " ")
    return F.array_join(F.slice(F.split(col.cast("string"), " ", -1), 1, 300), " ")


def sample_rows(df: DataFrame, schema: str, table: str, residue: int | None, k: int = 5) -> DataFrame:
    """column_id, pos, value of the first ``k`` rows in key order: a TakeOrderedAndProject over one pruned scan."""
    if residue is not None:
        df = df.filter(F.col("_key").isNull() | (F.col("_key") % 4 == residue))
    order = order_of(schema, table)
    cols = columns_of(schema, table)
    by = [F.col(c).asc_nulls_last() for c in order]
    top = df.orderBy(*by).limit(k).withColumn("_pos", F.row_number().over(Window.orderBy(*by)))  # k rows, which the limit has already brought together
    structs = [F.struct(F.lit(f"{schema}.{table}.{c}").alias("column_id"), F.col("_pos").alias("pos"), shown(F.col(c), t).alias("value")) for c, t in cols]
    return top.select(F.inline(F.array(*structs)))


def sample_values(spark: SparkSession, specs: list[Schema], residues: dict[str, int], k: int = 5) -> DataFrame:
    """column_id, pos, value of all tables of the schemas; each table is scanned once."""
    out = None
    for s in specs:
        for table in s.tables:
            rows = sample_rows(spark.sql(derived_sql(s.name, table)), s.name, table, residues[s.name], k)
            out = rows if out is None else out.union(rows)
    return out


def with_values(cat: Catalog, values: DataFrame) -> Catalog:
    """The catalog with its columns' ``values`` filled; nulls are skipped."""
    lists = values.filter("value is not null").groupBy("column_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "value"))), lambda x: x["value"]).alias("v"))
    columns = cat.columns.join(lists, "column_id", "left").withColumn("values", F.coalesce("v", F.array().cast("array<string>"))).select(cat.columns.columns)
    return Catalog(cat.tables, columns, cat.refs)
