"""Helpers that the operators share: the shared folder, written intermediate tables and sizes read from the plan."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: dict[str, str] = {}
BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share (``spark.checkpoint.dir``); a temporary one only where the setting is absent and all tasks run on this machine, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if "dir" not in _LOCAL:
        _LOCAL["dir"] = tempfile.mkdtemp(prefix="ctxmatch-")
        atexit.register(shutil.rmtree, _LOCAL["dir"], ignore_errors=True)
    return "file://" + _LOCAL["dir"]


def written(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet below the shared folder and read it again, which also cuts its lineage.

    A lost executor costs nothing afterwards, since the files outlive it. Void columns are not allowed.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    batch = spark.conf.get(BATCH)
    spark.conf.set(BATCH, min(int(batch), 1000) if int(batch) > 0 else 1000)  # rows hold whole texts: small batches bound Arrow's memory on both sides
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(BATCH, batch)
    return spark.read.schema(df.schema).parquet(path)


def drop_written(*tables: DataFrame) -> None:
    """Remove the files behind tables made by :func:`written`, once nothing reads them any more."""
    for df in tables:
        for file in df.inputFiles()[:1]:
            drop_folder(df.sparkSession, file.rsplit("/", 1)[0])


def drop_folder(spark: SparkSession, folder: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def text_of(name: str = "text") -> Column:
    """The text with null as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def plan_bytes(df: DataFrame) -> int:
    """The optimizer's estimate of the bytes of ``df``: file sizes for a scan. Only sizes task counts, never results."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def parts_for(df: DataFrame, bytes_each: int, least: int = 1) -> int:
    """How many tasks of about ``bytes_each`` the input needs; grows with the input. Without an estimate, the session's shuffle partitions."""
    size = plan_bytes(df)
    if size >= 1 << 60:  # what Spark assumes where it knows nothing
        return max(least, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return max(least, -(-size // bytes_each))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
