"""Tables and record collections."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, directory: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{directory}/{name}.parquet")


def records(df: DataFrame, id_col: str, text_cols: list[str]) -> DataFrame:
    """``(rec_id, text)``: attributes joined by blanks in the given order; nulls left out."""
    return df.select(F.col(id_col).alias("rec_id"), F.concat_ws(" ", *[F.col(c).cast("string") for c in text_cols]).alias("text"))


def strip_tags(html):
    return F.trim(F.regexp_replace(F.regexp_replace(html, r"<[^>]*>", " "), r"\s+", " "))


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A bucketed and sorted table, so that later joins on the key need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
