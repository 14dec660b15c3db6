"""Joins that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def range_join(points: DataFrame, ranges: DataFrame, point: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points with the ranges [lo, hi) that hold them: both meet in bins of ``width`` (an equi-join), the range is checked after.

    A range is copied once for each bin it touches, so ``width`` should be near the usual range; open ranges are bounded by the caller.
    """
    binned = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_bin", F.floor(F.col(point) / width)).join(binned, "_bin").filter((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("_bin")


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, take: list[str]) -> DataFrame:
    """``left`` with the columns ``take`` of the latest ``right`` row of the same key at or before its time: a union and one window, no pairs."""
    own = [c for c in left.columns if c not in (key, time)]
    a = left.select(key, time, F.lit(1).alias("_side"), *own, *[F.lit(None).cast(right.schema[c].dataType).alias(f"_r_{c}") for c in take])
    b = right.select(key, time, F.lit(0).alias("_side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in own], *[F.col(c).alias(f"_r_{c}") for c in take])
    upto = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    filled = a.union(b).select(key, time, "_side", *own, *[F.last(f"_r_{c}", True).over(upto).alias(c) for c in take])
    return filled.filter("_side = 1").drop("_side")


def salted(large: DataFrame, small: DataFrame, key: str, salts: int) -> DataFrame:
    """Equi-join in which every key of ``large`` is dealt to ``salts`` tasks and ``small`` is copied to them: for keys that hold a large share of the rows."""
    spread = large.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    copied = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return spread.join(copied, [key, "_salt"]).drop("_salt")


def pairs(rows: DataFrame, keys: list[str], value: str, tile: int = 2048) -> DataFrame:
    """Every pair ``a`` < ``b`` of ``value`` among the rows that agree in ``keys``, however far apart and however many.

    A group is cut by a hash of the value into bins of about ``tile`` rows. A bin is one array, and each row of the group is copied once for each bin: a copy that travels
    stands for ``tile`` pairs, no pair is shuffled, and a large group is dealt to as many places as it has bins. The merge join streams the copies past the arrays, so a task
    makes the pairs of one copy at a time; with the copies on the other side it would make those of a whole bin at once.
    """
    rows = rows.select(*keys, value).filter(F.col(value).isNotNull())
    sized = rows.join(rows.groupBy(*keys).agg(F.ceil(F.count("*") / tile).alias("_bins")), keys)
    places = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # given as a number: the engine would merge places by their input, which is small beside the pairs
    bins = sized.select(*keys, F.pmod(F.xxhash64(value), F.col("_bins")).alias("_bin"), value).repartition(places, *keys, "_bin").groupBy(*keys, "_bin").agg(F.collect_list(value).alias("_held"))
    copies = sized.select(*keys, F.explode(F.sequence(F.lit(0).cast("long"), F.col("_bins") - 1)).alias("_bin"), F.col(value).alias("a")).repartition(places, *keys, "_bin")
    return copies.hint("merge").join(bins, [*keys, "_bin"]).select("a", F.explode("_held").alias("b")).filter("a < b")
