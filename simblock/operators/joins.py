"""Joins that Spark has no operator for: as-of, interval and range joins by shuffled keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """Each left row with the ``value`` of the latest right row of its key at or before its time.

    One sort by key and time over the union of both sides; no pair is made.
    """
    both = left.withColumn("_v", F.lit(None).cast(dict(right.dtypes)[value])).withColumn("_t", F.lit(None).cast("timestamp")).withColumn("_right", F.lit(0))
    add = right.select(key, time, F.col(value).alias("_v"), F.col(time).alias("_t"), F.lit(1).alias("_right"))
    rows = both.unionByName(add, allowMissingColumns=True)
    order = Window.partitionBy(key).orderBy(time, F.desc("_right")).rowsBetween(Window.unboundedPreceding, 0)
    out = rows.withColumn("as_of_value", F.last("_v", ignorenulls=True).over(order)).withColumn("as_of_time", F.last("_t", ignorenulls=True).over(order))
    return out.where("_right = 0").drop("_v", "_t", "_right")


def interval(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of one key whose right time is within ``seconds`` after the left one.

    Rows meet on buckets as wide as the interval; a left row looks into two of them.
    """
    t = F.unix_micros(F.col(time).cast("timestamp"))
    width = seconds * 1_000_000
    l = left.withColumn("_b", F.explode(F.array(F.floor(t / width), F.floor(t / width) + 1)))  # noqa: E741
    r = right.withColumn("_b", F.floor(t / width))
    a, b = l.alias("l"), r.alias("r")
    gap = F.unix_micros(F.col(f"r.{time}").cast("timestamp")) - F.unix_micros(F.col(f"l.{time}").cast("timestamp"))
    return a.join(b, (F.col(f"l.{key}") == F.col(f"r.{key}")) & (F.col("l._b") == F.col("r._b")) & gap.between(0, width))


def band(left: DataFrame, right: DataFrame, left_col: str, right_col: str, width: float) -> DataFrame:
    """Pairs whose values differ by at most ``width``, met on buckets of that width."""
    l = left.withColumn("_b", F.explode(F.array(*[F.floor(F.col(left_col) / width) + d for d in (-1, 0, 1)])))  # noqa: E741
    r = right.withColumn("_b", F.floor(F.col(right_col) / width))
    return l.join(r, "_b").where(F.abs(F.col(left_col) - F.col(right_col)) <= width).drop("_b")
