"""Global order over many tasks: running sums and positions without a single-task window."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .stages import cut, shuffle_partitions


def running_totals(df: DataFrame, order: list[str], sums: dict[str, str], partitions: int | None = None, label: str = "ordered") -> DataFrame:
    """Add, for each row, the sum of a column over all rows before it in a total order.

    ``sums`` maps a new column to the (long) column that is summed. ``order`` must
    order rows totally, else rows that tie get an arbitrary mutual order. Rows are
    dealt by range; each range then adds the totals of the ranges before it, a table
    of one row for each range, so no task sees more than its own range.
    """
    n = partitions or shuffle_partitions(df.sparkSession)
    dealt = cut(df.repartitionByRange(n, *order).withColumn("_range", F.spark_partition_id()), label)
    totals = dealt.groupBy("_range").agg(*[F.sum(v).alias(f"_all_{k}") for k, v in sums.items()])
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("_range", *[F.coalesce(F.sum(f"_all_{k}").over(before), F.lit(0)).alias(f"_off_{k}") for k in sums])
    within = Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    local = dealt.select("*", *[F.coalesce(F.sum(v).over(within), F.lit(0)).alias(f"_loc_{k}") for k, v in sums.items()])
    out = local.join(F.broadcast(offsets), "_range")  # one row for each range
    return out.select(*df.columns, *[(F.col(f"_loc_{k}") + F.col(f"_off_{k}")).alias(k) for k in sums])
