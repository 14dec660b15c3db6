"""Training as Spark tasks: one group per (model, fold, run), so that all models of all runs train side by side."""

from __future__ import annotations

import zlib
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.cut import cut
from .mlp import Adam, Mlp, TrainConfig

KINDS = ("SINGLE", "PAIR", "HOLO")
MODEL = "model_id string, fold int, run int, dims array<int>, outputs array<string>, weights binary, score double, recalls array<double>"
#: Cutoffs t of the validation recalls.
VALIDATION = (1, 2, 3, 4, 5)


def specs(kind: str, schemas: list[str]) -> dict[str, tuple[str, ...]]:
    """model id -> its schemas: each alone, each pair, or all."""
    names = sorted(schemas)
    if kind == "SINGLE":
        return {f"SINGLE:{s}": (s,) for s in names}
    if kind == "PAIR":
        return {f"PAIR:{a}+{b}": (a, b) for a, b in combinations(names, 2)}
    return {"HOLO": tuple(names)}


def count(kind: str, schemas: int) -> int:
    return {"SINGLE": schemas, "PAIR": schemas * (schemas - 1) // 2, "HOLO": 1}[kind]


def with_folds(rac: DataFrame, k: int = 5, *, group_by_column: bool = False) -> DataFrame:
    """``fold``: rows of a stratum (schema, origin table) dealt in the order of a hash; ``group_by_column`` keeps all views of a column in one fold."""
    if group_by_column:
        return rac.withColumn("fold", (F.conv(F.substring(F.md5("column_id"), 1, 8), 16, 10).cast("long") % k).cast("int"))
    order = Window.partitionBy("schema_id", "origin_table").orderBy(F.md5(F.concat("view_id", "column_id")), "view_id", "column_id")
    return rac.withColumn("fold", ((F.row_number().over(order) - 1) % k).cast("int"))


def matrices(rows: pd.DataFrame, outputs: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vectors, soft labels, mask of the row's own schema's outputs)."""
    at = {o: i for i, o in enumerate(outputs)}
    own = np.array([o.split(".")[0] for o in outputs])
    y = np.zeros((len(rows), len(outputs)))
    for i, (schema, label) in enumerate(zip(rows["schema_id"], rows["y"], strict=True)):
        for table, weight in (label.items() if isinstance(label, dict) else label):
            y[i, at[f"{schema}.{table}"]] = weight
    mask = (rows["schema_id"].to_numpy()[:, None] == own[None]).astype(float)
    return np.array(rows["x"].tolist(), float).reshape(len(rows), -1), y, mask


def validation(p: np.ndarray, mask: np.ndarray, origin: np.ndarray) -> list[float]:
    """Share of held-out rows whose origin table is among the first t of their own schema's outputs, for each t of ``VALIDATION``; ties by output."""
    order = np.argsort(-np.where(mask > 0, p, -1.0), axis=1, kind="stable")
    place = (order == origin[:, None]).argmax(1)
    return [float(np.mean(place < t)) for t in VALIDATION]


def train(rac: DataFrame, tables: DataFrame, kind: str, *, config: TrainConfig = TrainConfig(), runs: int = 1, group_by_column: bool = False, tag: str = "") -> DataFrame:
    """A row per trained model: MODEL. ``rac``: schema_id, view_id, column_id, origin_table, x, y; ``tables``: schema_id, table_id (metadata, read on the driver).

    Rows are copied to every task that needs them; the mask keeps a row's loss to its own schema's outputs.
    """
    spark = rac.sparkSession
    names = [f"{r.schema_id}.{r.table_id}" for r in tables.select("schema_id", "table_id").orderBy("schema_id", "table_id").collect()]
    models = specs(kind, sorted({n.split(".")[0] for n in names}))
    tasks = spark.createDataFrame([(m + tag, s, f, r) for m, own in models.items() for s in own for f in range(config.folds) for r in range(runs)], "model_id string, schema_id string, task_fold int, run int")
    outputs = {m + tag: [n for n in names if n.split(".")[0] in own] for m, own in models.items()}
    rows = with_folds(rac, config.folds, group_by_column=group_by_column).select("schema_id", "origin_table", "view_id", "column_id", F.col("x").cast("array<double>").alias("x"), F.map_entries("y").alias("y"), "fold")

    def fit(key, pdf: pd.DataFrame) -> pd.DataFrame:
        model, fold, run = key
        pdf = pdf.sort_values(["schema_id", "view_id", "column_id"]).assign(y=lambda d: d["y"].map(lambda e: {p["key"]: p["value"] for p in e}))
        own, x_y_m = outputs[model], None
        learn, held = pdf[pdf["fold"] != fold], pdf[pdf["fold"] == fold]
        learn = learn if len(learn) else pdf
        x_y_m = matrices(learn, own)
        dims = (x_y_m[0].shape[1], *config.hidden, len(own))
        seed = zlib.crc32(f"{model}|{fold}|{run}".encode())
        other = matrices(held, own) if len(held) else None
        net = Mlp(dims, seed).fit(*x_y_m, config, seed, other)
        recalls = [0.0] * len(VALIDATION)
        if other is not None:
            origin = np.array([own.index(f"{s}.{t}") for s, t in zip(held["schema_id"], held["origin_table"], strict=True)])
            recalls = validation(net.forward(other[0])[0], other[2], origin)
        return pd.DataFrame({"model_id": [model], "fold": [fold], "run": [run], "dims": [list(dims)], "outputs": [own], "weights": [net.to_bytes()], "score": [recalls[0]], "recalls": [recalls]})

    return tasks.join(rows, "schema_id").groupBy("model_id", "task_fold", "run").applyInPandas(fit, MODEL)


def save(models: DataFrame, path: str) -> None:
    models.write.mode("overwrite").parquet(path)


def load(spark, path: str) -> DataFrame:
    return spark.read.schema(MODEL).parquet(path)


def gradient_step(rows: DataFrame, net: Mlp, outputs: list[str], config: TrainConfig) -> tuple[list[np.ndarray], list[np.ndarray]] | None:
    """The gradient over a distributed table (schema_id, x, y), None if it is empty: sums of each partition, added again by fewer tasks before the driver adds the rest."""
    shared = rows.sparkSession.sparkContext.broadcast(net)

    def partial(batches):
        total, n = 0.0, 0
        for pdf in batches:
            if len(pdf):
                pdf = pdf.assign(y=pdf["y"].map(lambda e: {p["key"]: p["value"] for p in e}))
                dw, db = shared.value.gradients(*matrices(pdf, outputs), config)
                total, n = total + np.concatenate([a.ravel() for a in dw + db]) * len(pdf), n + len(pdf)
        if n:
            yield pd.DataFrame({"g": [total.tobytes()], "n": [n]})

    def added(batches):
        found = [(np.frombuffer(g), n) for pdf in batches for g, n in zip(pdf["g"], pdf["n"], strict=True)]
        if found:
            yield pd.DataFrame({"g": [sum(g for g, _ in found).tobytes()], "n": [sum(n for _, n in found)]})

    pieces = rows.select("schema_id", F.col("x").cast("array<double>").alias("x"), F.map_entries("y").alias("y")).mapInPandas(partial, "g binary, n long")
    fewer = max(1, int(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")) ** 0.5))
    found = pieces.repartition(fewer).mapInPandas(added, "g binary, n long").collect()  # a gradient from each of few tasks
    shared.unpersist()
    if not found:
        return None
    flat, out, at = sum(np.frombuffer(r.g) for r in found) / sum(r.n for r in found), [], 0
    for a in net.w + net.b:
        out.append(flat[at : at + a.size].reshape(a.shape))
        at += a.size
    return out[: len(net.w)], out[len(net.w) :]


def batch_of(epoch: int, batches: int):
    """Which batch of an epoch a row is in, by a hash: the same rows meet others in every epoch."""
    return F.pmod(F.xxhash64(F.lit(epoch), "schema_id", "view_id", "column_id"), F.lit(batches))


def train_distributed(rac: DataFrame, outputs: list[str], config: TrainConfig, *, epochs: int = 1, seed: int = 0) -> Mlp:
    """Mini-batch Adam over a table that no task could hold: the rows of a batch stay where they are, and their gradients are added.

    A step is a job, so ``config.batch`` should be thousands of rows; dropout and early stopping are left to the trainer in one task. The driver holds the weights.
    """
    rows = cut(rac.select("schema_id", "view_id", "column_id", "x", "y"))
    size = rows.agg(F.count("*"), F.max(F.size("x"))).first()
    batches = max(1, -(-size[0] // config.batch))
    net, adam = Mlp((size[1], *config.hidden, len(outputs)), seed), Adam(config)
    for epoch in range(epochs):
        for number in range(batches):
            found = gradient_step(rows.filter(batch_of(epoch, batches) == number), net, outputs, config)
            if found is not None:
                adam.step(net.w + net.b, found[0] + found[1])
    return net


def mllib_baseline(rac: DataFrame) -> DataFrame:
    """A sanity baseline: held-out accuracy of spark.ml's multinomial logistic regression on the origin table."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import StringIndexer
    from pyspark.ml.functions import array_to_vector

    rows = with_folds(rac).select(F.concat_ws(".", "schema_id", "origin_table").alias("t"), array_to_vector(F.col("x").cast("array<double>")).alias("features"), "fold")
    rows = StringIndexer(inputCol="t", outputCol="label").fit(rows).transform(rows)
    model = LogisticRegression(maxIter=15, regParam=0.01).fit(rows.filter("fold <> 0"))
    return model.transform(rows.filter("fold = 0")).agg(F.count("*").alias("rows"), F.round(F.avg((F.col("prediction") == F.col("label")).cast("double")), 4).alias("accuracy"))
