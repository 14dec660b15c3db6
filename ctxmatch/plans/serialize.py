"""Columns and tables as sentences for the encoder."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.catalog import Catalog

KINDS = ("META", "VALS", "NOTAB", "REF")


@dataclass(frozen=True)
class Options:
    """``anchors``: lead each part with its word; ``marks``: start and separator marks; ``values``: how many; ``value_tokens``: budget of all values together; ``tokens``: of the sentence."""

    anchors: bool = True
    marks: bool = True
    values: int = 5
    value_tokens: int = 300
    tokens: int = 512
    missing: str = "None"


def _cut(col: Column, tokens: int) -> Column:
    return F.array_join(F.slice(F.split(col, " "), 1, tokens), " ")


def _sentence(parts: list[tuple[str, Column]], options: Options) -> Column:
    shown = [F.concat(F.lit(f"{word} " if options.anchors else ""), F.coalesce(F.nullif(part, F.lit("")), F.lit(options.missing))) for word, part in parts]
    text = F.concat_ws(" [SEP] " if options.marks else " ", *shown)
    return _cut(F.concat(F.lit("[CLS] "), text) if options.marks else text, options.tokens)


def column(kind: str = "META", options: Options = Options()) -> Column:
    """Of an augmented column's fields: META has name, view, type and constraint; VALS adds values; NOTAB is VALS without the view; REF is VALS with the neighbours."""
    if kind not in KINDS:
        raise ValueError(f"kind is one of {KINDS}")
    parts = [("column", F.col("column_name")), ("table", F.col("view_name")), ("type", F.col("dtype")), ("constraint", F.col("constraint"))]
    if kind == "NOTAB":
        del parts[1]
    if kind != "META":
        parts.append(("values", _cut(F.array_join(F.slice("values", 1, options.values), ", "), options.value_tokens)))
    if kind == "REF":
        parts += [("weak tables", F.array_join("weak", ", ")), ("strong tables", F.array_join("strong", ", "))]
    return _sentence(parts, options)


def table(cat: Catalog, options: Options = Options()) -> DataFrame:
    """schema_id, table_id, text (TABDOC): name, keys with types, foreign keys with what they reference, other columns with types."""
    by = F.transform(F.sort_array(F.collect_list(F.struct("ordinal", "column_name", "dtype", "is_pk", "fk_refs"))), lambda x: x)
    rows = cat.columns.groupBy("schema_id", "table_id").agg(by.alias("c"))
    typed = lambda x: F.concat(x["column_name"], F.lit(" "), x["dtype"])
    key = F.transform(F.filter("c", lambda x: x["is_pk"]), typed)
    foreign = F.transform(F.filter("c", lambda x: F.size(x["fk_refs"]) > 0), lambda x: F.concat(typed(x), F.lit(" references "), x["fk_refs"][0]["table"], F.lit(" "), x["fk_refs"][0]["column"]))
    rest = F.transform(F.filter("c", lambda x: ~x["is_pk"] & (F.size(x["fk_refs"]) == 0)), typed)
    parts = [("table", F.col("table_id")), ("keys", F.array_join(key, ", ")), ("foreign keys", F.array_join(foreign, ", ")), ("columns", F.array_join(rest, ", "))]
    return rows.select("schema_id", "table_id", _sentence(parts, options).alias("text"))
