"""Keys and references that a catalog does not declare, found in the data."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

REFERENCES = "weak_table string, weak_column string, strong_table string, strong_column string"


def _cells(df: DataFrame, named: dict[str, Column]) -> DataFrame:
    """name, v: a row for each named value of each row; all names share what follows."""
    return df.select(F.explode(F.array(*[F.struct(F.lit(n).alias("column_name"), v.alias("v")) for n, v in named.items()])).alias("x")).select("x.*")


def unique_counts(df: DataFrame, table: str) -> DataFrame:
    """table_id, column_name, n_rows, n_distinct, is_key: exact counts of all columns from one scan.

    Cells are counted by (column, value), partially before the exchange, so no value's rows meet in one task and columns share the shuffle.
    """
    rows = _cells(df, {c: F.col(c).cast("string") for c in df.columns}).groupBy("column_name", "v").agg(F.count("*").alias("_n"))
    rows = rows.groupBy("column_name").agg(F.sum("_n").alias("all_rows"), F.sum(F.when(F.col("v").isNotNull(), F.col("_n")).otherwise(0)).alias("n_rows"), F.count("v").alias("n_distinct"))
    return rows.select(F.lit(table).alias("table_id"), "column_name", "n_rows", "n_distinct", (F.col("all_rows") == F.col("n_distinct")).alias("is_key"))


def candidate_keys(df: DataFrame, max_arity: int = 2, *, approx: bool = True) -> DataFrame:
    """columns (array), arity: minimal sets of up to ``max_arity`` columns without nulls whose values tell all rows apart.

    With ``approx`` one pass estimates distinct values, and only sets whose estimates multiply to half of the rows or more are counted exactly (the estimates err
    by a few per cent); each arity is one exchange for all its sets. The driver reads one number for each column and set.
    """
    names = df.columns
    first = df.agg(F.count("*").alias("_rows"), *[F.approx_count_distinct(c).alias(c) for c in names], *[F.count(c).alias(f"_{c}") for c in names]).first()
    rows, whole = first["_rows"], [c for c in names if first[f"_{c}"] == first["_rows"]]
    keys: list[tuple[str, ...]] = []
    for arity in range(1, max_arity + 1):
        sets = [s for s in combinations(whole, arity) if not any(set(k) <= set(s) for k in keys)]
        if approx:
            sets = [s for s in sets if 2 * _product(first[c] for c in s) >= rows]
        if not sets or not rows:
            continue
        counted = _cells(df, {",".join(s): F.to_json(F.struct(*s)) for s in sets}).distinct().groupBy("column_name").count()
        keys += sorted(tuple(r["column_name"].split(",")) for r in counted.collect() if r["count"] == rows)
    return df.sparkSession.createDataFrame([(list(k), len(k)) for k in keys], "columns array<string>, arity int")


def _product(values) -> int:
    out = 1
    for v in values:
        out *= v
    return out


def references(tables: dict[str, DataFrame], keys: list[tuple[str, str]]) -> DataFrame:
    """weak_table, weak_column, strong_table, strong_column: columns whose values all are values of a key of another table, of the same type.

    Pairs are pruned by type, least and greatest value and estimated distinct values (one pass a table; a row a column on the driver); what is left shares one exchange, in which
    values meet with the columns that hold them.
    """
    facts = {}
    for name, df in tables.items():
        kinds = {c: t for c, t in df.dtypes if t in ("int", "bigint", "string", "date")}
        row = df.agg(*[f(c).alias(f"{n}_{c}") for c in kinds for n, f in (("least", F.min), ("most", F.max), ("n", F.approx_count_distinct))]).first()
        facts |= {(name, c): ("bigint" if t == "int" else t, row[f"least_{c}"], row[f"most_{c}"], row[f"n_{c}"]) for c, t in kinds.items()}
    fits = lambda w, s: w[0] == s[0] and w[1] is not None and s[1] is not None and w[1] >= s[1] and w[2] <= s[2] and w[3] <= 1.2 * s[3]
    pairs = [(*w, *s) for w in facts for s in keys if w[0] != s[0] and fits(facts[w], facts[s])]
    found = orphans(tables, pairs) if pairs else None
    return found.filter("orphans = 0").drop("orphans") if found is not None else next(iter(tables.values())).sparkSession.createDataFrame([], REFERENCES)


def orphans(tables: dict[str, DataFrame], pairs: list[tuple[str, str, str, str]]) -> DataFrame:
    """weak/strong table and column, orphans: distinct weak values without a key. All pairs share one exchange: values are tagged by column and meet by value."""
    cells = None
    for t, c in sorted({(wt, wc) for wt, wc, _, _ in pairs} | {(st, sc) for _, _, st, sc in pairs}):
        rows = tables[t].select(F.col(c).cast("string").alias("v")).filter("v is not null").distinct().select("v", F.lit(f"{t}.{c}").alias("owner"))
        cells = rows if cells is None else cells.union(rows)
    owners = cells.groupBy("v").agg(F.collect_set("owner").alias("owners"))  # at most as many as columns
    listed = cells.sparkSession.createDataFrame(pairs, "weak_table string, weak_column string, strong_table string, strong_column string").withColumns({"w": F.concat_ws(".", "weak_table", "weak_column"), "s": F.concat_ws(".", "strong_table", "strong_column")})
    missing = owners.select("owners", F.explode("owners").alias("w")).join(F.broadcast(listed.select("w", "s")), "w").filter(~F.array_contains("owners", F.col("s"))).groupBy("w", "s").agg(F.count("*").alias("orphans"))
    return listed.join(missing, ["w", "s"], "left").select("weak_table", "weak_column", "strong_table", "strong_column", F.coalesce("orphans", F.lit(0)).cast("long").alias("orphans"))
