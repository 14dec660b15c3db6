"""Streaming queries, run to the end of their source so that a batch statement can be their twin."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..functions import encode
from ..operators import block
from ..plans import augment, serialize
from ..plans.cut import cut
from ..sources.io import shared_dir
from ..streaming.runs import each_batch, finished, replay
from . import query, sql
from .methods import four


def _events(spark, sf_dir):
    return replay(spark, sf_dir, "events", "ts")


@query("SELECT ts::DATE AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def st_tumbling(spark, sf_dir):
    rows = _events(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return finished(rows.select(F.to_date("w.start").alias("day"), "event_type", "n"), "complete")


@query("SELECT (ts::DATE - d.d::INT)::DATE AS day, count(*) AS n FROM events, (VALUES (0), (1)) AS d(d) GROUP BY 1")
def st_sliding(spark, sf_dir):
    rows = _events(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return finished(rows.select(F.to_date("w.start").alias("day"), "n"), "complete")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, k::BIGINT AS session, count(*) AS n FROM s GROUP BY ALL")
def st_session(spark, sf_dir):
    from pyspark.sql.window import Window

    rows = _events(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n"))
    done = finished(rows.select("user_id", F.col("w.start").alias("start"), "n"), "complete")
    return done.select("user_id", F.row_number().over(Window.partitionBy("user_id").orderBy("start")).cast("long").alias("session"), "n")


def late_events(spark, sf_dir) -> DataFrame:
    """The events in two triggers, the last two days in the second, and in a third those of the first five days once more.

    What is late is told by the watermark of the trigger before the last, so the last days come apart.
    """
    folder = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    spanned = rows.join(F.broadcast(rows.agg(F.min("ts").alias("t0"), F.max("ts").alias("t1"))))
    recent = F.col("ts") >= F.col("t1") - F.expr("interval 2 days")
    for part, wanted in enumerate((~recent, recent, F.col("ts") < F.col("t0") + F.expr("interval 5 days"))):
        spanned.filter(wanted).select(*rows.columns).coalesce(1).write.parquet(f"{folder}/{part}")
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder)


def closed_days(spark, sf_dir, seen: list | None = None) -> DataFrame:
    days = late_events(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return finished(days.select(F.to_date("w.start").alias("day"), "n"), "append", seen)


@query("SELECT ts::DATE AS day, count(*) AS n FROM events GROUP BY 1 HAVING ts::DATE + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
def st_watermark_late(spark, sf_dir):
    """Days that the watermark has closed. The first days come a second time, too late: they are dropped, not counted twice."""
    return closed_days(spark, sf_dir)


@query("SELECT DISTINCT user_id, event_type FROM events")
def st_dedup(spark, sf_dir):
    return finished(_events(spark, sf_dir).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"), "append")


@query("SELECT c_mktsegment AS segment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def st_static_join(spark, sf_dir):
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return finished(_events(spark, sf_dir).join(customers, "user_id").groupBy("segment").agg(F.count("*").alias("n")), "complete")


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type <> b.event_type AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def st_stream_join(spark, sf_dir):
    side = lambda p: _events(spark, sf_dir).select(F.col("event_id").alias(f"{p}_id"), F.col("user_id").alias(f"{p}_user"), F.col("event_type").alias(f"{p}_type"), F.col("ts").alias(f"{p}_ts")).withWatermark(f"{p}_ts", "2 hours")
    on = (F.col("a_user") == F.col("b_user")) & (F.col("a_type") != F.col("b_type")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("interval 1 hour"))
    return finished(side("a").join(side("b"), on).select(F.col("a_id").alias("first"), F.col("b_id").alias("second")), "append")


@query("SELECT user_id, count(*) AS seen, count(*) >= 50 AS retrain FROM events GROUP BY 1")
def st_state(spark, sf_dir):
    """Per user: how many events were seen, and whether they have passed the bound at which a model would be trained anew."""

    def step(key, batches, state):
        seen = state.get[0] if state.exists else 0
        seen += sum(len(b) for b in batches)
        state.update((seen,))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [seen], "retrain": [seen >= 50]})

    rows = _events(spark, sf_dir).groupBy("user_id").applyInPandasWithState(step, "user_id long, seen long, retrain boolean", "seen long", "update", GroupStateTimeout.NoTimeout)
    return finished(rows, "update")


@query(
    f"WITH RECURSIVE {sql.SIMDOC}, dots AS (SELECT c.column_id AS query, t.schema_id || '.' || t.table_id AS candidate, sum(c.value * t.value) AS s FROM ch c JOIN th t ON c.bucket = t.bucket GROUP BY ALL)"
    f" SELECT query, candidate, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY query ORDER BY score DESC, candidate)::INT AS rank FROM (SELECT c.column_id AS query, t.schema_id || '.' || t.table_id AS candidate, {sql.cosine('s')} AS score FROM cols c CROSS JOIN tabs t LEFT JOIN dots d ON d.query = c.column_id AND d.candidate = t.schema_id || '.' || t.table_id)) WHERE rank <= 2"
)
def st_foreach_batch(spark, sf_dir):
    """Columns announced in a stream: every micro-batch is encoded and its two nearest tables are stored under the batch's number."""
    cat, folder = four(spark), f"{shared_dir(spark)}/announced-{uuid.uuid4().hex}"
    augment.build(cat, d_max=1, kind="META").select("schema_id", "column_id", "text").repartition(2).write.parquet(f"{folder}/in")
    docs = cut(encode.word_vectors(serialize.table(cat).select(F.concat_ws(".", "schema_id", "table_id").alias("neighbour"), "text"), ["neighbour"], "text"))

    def step(batch, number):
        cols = encode.word_vectors(batch, ["column_id"], "text").withColumnRenamed("column_id", "query")
        top = block.knn(cols, docs, 2, metric="cosine").withColumnsRenamed({"neighbour": "candidate", "dist": "score"})
        top.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    each_batch(spark.readStream.schema("schema_id string, column_id string, text string").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in"), step)
    return spark.read.parquet(f"{folder}/out").select("query", "candidate", "score", "rank")
