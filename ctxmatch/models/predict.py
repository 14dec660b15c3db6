"""Prediction: which tables of a target schema a source column belongs to."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.block import ranked
from .mlp import Mlp

SCORES = "run int, source_schema string, column_id string, target_schema string, table_id string, p double"


#: Bytes of weights that go to every task; models beyond it meet blocks of ``COLUMNS`` columns instead.
BROADCAST_BYTES, COLUMNS = 128 << 20, 20_000


def base_of(kind: str, source: str, target: str) -> str:
    """The model that answers for a pair of schemas: the target's own, the pair's, or the one of all."""
    return "HOLO" if kind == "HOLO" else f"SINGLE:{target}" if kind == "SINGLE" else "PAIR:" + "+".join(sorted((source, target)))


class Folds:
    """Models of one base name, ready to run: for each run the outputs of a target schema, averaged over folds."""

    def __init__(self, rows: list[dict]):
        self.nets = [(int(r["run"]), Mlp.from_bytes(tuple(r["dims"]), r["weights"]), list(r["outputs"])) for r in sorted(rows, key=lambda r: (r["run"], r["fold"]))]

    def answer(self, x: np.ndarray, target: str) -> Iterator[tuple[int, list[str], np.ndarray]]:
        """(run, tables, probabilities): of the last layer only the target's outputs are multiplied."""
        for run in sorted({r for r, _, _ in self.nets}):
            total, n = 0.0, 0
            for r, net, names in self.nets:
                if r == run:
                    own = np.array([i for i, name in enumerate(names) if name.split(".")[0] == target], int)
                    tables = [names[i].split(".", 1)[1] for i in own]
                    total, n = total + net.forward(x, own)[0], n + 1
            yield run, tables, total / n


def _answers(models: dict[str, Folds], kind: str, asked: dict[str, list[str]], columns: pa.Table) -> Iterator[pa.RecordBatch]:
    names = ["run", "source_schema", "column_id", "target_schema", "table_id", "p"]
    flat = columns.column("x").combine_chunks()
    x = np.asarray(flat.flatten(), float).reshape(len(columns), -1)
    schemas, ids = np.array(columns.column("schema_id").to_pylist()), np.array(columns.column("column_id").to_pylist(), object)
    for source in np.unique(schemas):
        at = np.flatnonzero(schemas == source)
        for target in asked.get(source, []):
            folds = models.get(base_of(kind, source, target))
            for run, tables, p in folds.answer(x[at], target) if folds else ():
                n, m = p.shape
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n * m, run, np.int32)), pa.array([source] * (n * m)), pa.array(np.repeat(ids[at], m)), pa.array([target] * (n * m)), pa.array(tables * n, pa.string()), pa.array(p.ravel())], names)


def scores(columns: DataFrame, models: DataFrame, kind: str, pairs: DataFrame, *, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """SCORES of original columns (schema_id, column_id, x) for the asked (source_schema, target_schema) pairs (metadata, read on the driver), averaged over folds.

    SINGLE uses the target's model, PAIR the pair's, HOLO the one of all. Models of up to ``broadcast_bytes`` go to the tasks, and columns are scored where they lie, in
    one pass without a shuffle. Otherwise columns meet the models they need in blocks of ``COLUMNS``, one model's folds in a task.
    """
    asked: dict[str, list[str]] = {}
    for r in sorted(map(tuple, pairs.select("source_schema", "target_schema").distinct().collect())):
        asked.setdefault(r[0], []).append(r[1])
    columns = columns.select("schema_id", "column_id", F.col("x").cast("array<double>").alias("x"))
    models = models.withColumn("base", F.regexp_replace("model_id", "[(].*", ""))
    if (models.agg(F.sum(F.octet_length("weights"))).first()[0] or 0) <= broadcast_bytes:
        grouped: dict[str, list[dict]] = {}
        for r in models.select("base", "run", "fold", "dims", "outputs", "weights").collect():  # checked above
            grouped.setdefault(r["base"], []).append(r.asDict())
        shared = columns.sparkSession.sparkContext.broadcast({base: Folds(rows) for base, rows in grouped.items()})

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if batch.num_rows:
                    yield from _answers(shared.value, kind, asked, pa.Table.from_batches([batch]))

        return columns.mapInArrow(run, SCORES)
    blocks = max(1, -(-columns.count() // COLUMNS))
    needs = columns.sparkSession.createDataFrame([(a, t, base_of(kind, a, t)) for a, ts in asked.items() for t in ts], "schema_id string, target_schema string, base string")
    work = columns.join(F.broadcast(needs), "schema_id").withColumn("block", F.pmod(F.xxhash64("column_id"), F.lit(blocks)).cast("int"))
    weights = models.select("base", "run", "fold", "dims", "outputs", "weights").withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def forward(key: tuple, cols: pa.Table, rows: pa.Table) -> pa.Table:
        found = []
        if len(cols) and len(rows):
            models = {key[0].as_py(): Folds(rows.to_pylist())}
            for target in cols.column("target_schema").unique().to_pylist():
                part = cols.filter(pa.compute.equal(cols.column("target_schema"), target))
                found += _answers(models, kind, {s: [target] for s in asked}, part)
        return pa.Table.from_batches(found) if found else _EMPTY

    return work.groupBy("base", "block").cogroup(weights.groupBy("base", "block")).applyInArrow(forward, SCORES)


_EMPTY = pa.table({"run": pa.array([], pa.int32()), **{c: pa.array([], pa.string()) for c in ("source_schema", "column_id", "target_schema", "table_id")}, "p": pa.array([], pa.float64())})


def top_tables(found: DataFrame, t: int | None = None) -> DataFrame:
    """Ranked by probability without a threshold; ties by table."""
    return ranked(found.withColumn("p", F.round("p", 6)), ["run", "column_id", "target_schema"], [F.col("p").desc(), F.col("table_id")], t)


def above(found: DataFrame, threshold: float) -> DataFrame:
    """The rejected option: every table of at least this probability."""
    return found.filter(F.col("p") >= threshold)
