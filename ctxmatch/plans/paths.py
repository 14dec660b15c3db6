"""Shortest join paths as views."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData
from pyspark.sql import functions as F

from ..sources.catalog import Catalog
from .cut import cut


def views(edges: DataFrame, tables: DataFrame, d_max: int, *, ties: str = "one", keys: tuple[str, ...] = ("schema_id",), dedup_orientation: bool = False, how: str = "group") -> DataFrame:
    """keys, view_id, path, n_tables: a shortest path for each ordered pair of tables that one of at most ``d_max`` tables connects.

    Of tied shortest paths the smallest in table order stays (``ties='one'``), or all of them. ``keys`` tell independent graphs apart: each is searched breadth first in
    one task (``how='group'``), all side by side, since a schema's tables fit one. For a graph that does not, ``how='join'`` grows the paths by joins with the edges.
    """
    found = _searched(edges, tables, d_max, ties, keys) if how == "group" else _joined(edges, tables, d_max, ties, keys)
    if dedup_orientation:
        found = found.filter(F.col("path") <= F.reverse("path"))
    return found.select(*keys, F.array_join("path", ">").alias("view_id"), "path", F.size("path").alias("n_tables"))


def _graphs(edges: DataFrame, tables: DataFrame, keys: tuple[str, ...]) -> GroupedData:
    """Rows (keys, src, dst) by graph: its edges, and every table once without a dst."""
    return tables.select(*keys, F.col("table_id").alias("src"), F.lit(None).cast("string").alias("dst")).union(edges.select(*keys, "src", "dst")).groupBy(*keys)


def _levels(rows: pa.Table) -> Iterator[Iterator[dict[str, list[str]]]]:
    """For every table, the tables found newly at each further step, with all their predecessors on shortest paths."""
    links: dict[str, set[str]] = {}
    for a, b in zip(rows.column("src").to_pylist(), rows.column("dst").to_pylist(), strict=True):
        links.setdefault(a, set()).update([b] if b is not None else [])

    def search(start: str) -> Iterator[dict[str, list[str]]]:
        seen, front = {start}, {start: []}
        while front:
            yield front
            reached: dict[str, list[str]] = {}
            for a in sorted(front):
                for b in links.get(a, ()):
                    if b not in seen:
                        reached.setdefault(b, []).append(a)
            seen.update(reached)
            front = reached

    for start in sorted(links):
        yield search(start)


def _searched(edges: DataFrame, tables: DataFrame, d_max: int, ties: str, keys: tuple[str, ...]) -> DataFrame:
    kinds = [tables.schema[k].dataType.simpleString() for k in keys]

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        out: list[list[str]] = []
        for levels in _levels(rows):
            paths: dict[str, list[list[str]]] = {}
            for front in islice(levels, d_max):
                paths = {b: [*([p + [b] for a in before for p in paths[a]] or [[b]])] for b, before in front.items()}
                if ties == "one":
                    paths = {b: [min(ps)] for b, ps in paths.items()}
                out += [p for ps in paths.values() for p in ps]
        return pa.table([*(pa.array([k.as_py()] * len(out), k.type) for k in key), pa.array(out, pa.list_(pa.string()))], names=[*keys, "path"])

    return _graphs(edges, tables, keys).applyInArrow(run, ", ".join(f"{k} {t}" for k, t in zip(keys, kinds, strict=True)) + ", path array<string>")


def _joined(edges: DataFrame, tables: DataFrame, d_max: int, ties: str, keys: tuple[str, ...]) -> DataFrame:
    """Each round joins the newest paths with the edges and drops pairs that are settled; what a round finds and what is settled are checkpointed."""
    k = list(keys)
    front = cut(tables.select(*k, F.col("table_id").alias("src"), F.col("table_id").alias("dst"), F.array("table_id").alias("path")))
    settled = front
    step = edges.select(*k, F.col("src").alias("dst"), F.col("dst").alias("next"))
    for _ in range(1, d_max):
        reached = front.join(step, [*k, "dst"]).filter(~F.array_contains("path", F.col("next"))).select(*k, "src", F.col("next").alias("dst"), F.concat("path", F.array("next")).alias("path"))
        reached = reached.join(settled.select(*k, "src", "dst").distinct(), [*k, "src", "dst"], "left_anti")
        front = cut(reached.groupBy(*k, "src", "dst").agg(F.min("path").alias("path")) if ties == "one" else reached)
        if front.isEmpty():
            break
        settled = cut(settled.union(front))
    return settled


def estimate(edges: DataFrame, tables: DataFrame, d_max: int, *, keys: tuple[str, ...] = ("schema_id",), budget: int | None = None) -> DataFrame:
    """keys, depth, pairs: how many table pairs each depth would add, counted without making any path.

    With a ``budget`` a graph's count stops at the first depth that exceeds it: callers see that before views are made and expanded to columns.
    """
    kinds = [tables.schema[k].dataType.simpleString() for k in keys]

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        searches, counts = list(_levels(rows)), []
        for _ in range(d_max):
            counts.append(sum(len(next(levels, ())) for levels in searches))
            if not counts[-1] or budget is not None and sum(counts) > budget:
                break
        counts = [(d, n) for d, n in enumerate(counts, 1) if n]
        return pa.table([*(pa.array([k.as_py()] * len(counts), k.type) for k in key), pa.array([d for d, _ in counts], pa.int32()), pa.array([n for _, n in counts], pa.int64())], names=[*keys, "depth", "pairs"])

    return _graphs(edges, tables, keys).applyInArrow(run, ", ".join(f"{k} {t}" for k, t in zip(keys, kinds, strict=True)) + ", depth int, pairs long")


def materialise(path: list[str], cat: Catalog, rows: Callable[[str], DataFrame], *, how: str = "inner", limit: int | None = None) -> DataFrame:
    """The view itself: tables joined along the references between neighbours on the path; columns are named ``table.column``, both keys stay.

    Reads the references among the path's tables (metadata) on the driver to build the join.
    """
    refs = cat.refs.filter(F.col("strong_table").isin(path) & F.col("weak_table").isin(path)).collect()
    named = lambda t: (df := rows(t)).select(*[F.col(c).alias(f"{t}.{c}") for c in df.columns])
    out = named(path[0])
    for a, b in zip(path, path[1:], strict=False):
        links = sorted((r.strong_column, r.weak_column, r.strong_table) for r in refs if {r.strong_table, r.weak_table} == {a, b})
        if not links:
            raise ValueError(f"no reference between {a} and {b}")
        strong, weak, strong_table = links[0]
        left, right = (strong, weak) if strong_table == a else (weak, strong)
        out = out.join(named(b), F.col(f"`{a}.{left}`") == F.col(f"`{b}.{right}`"), how)
    return out.limit(limit) if limit is not None else out
