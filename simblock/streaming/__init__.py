"""Incremental blocking and the stream operators around it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.stages import fresh_path


def replay(spark: SparkSession, df: DataFrame, files: int = 4) -> DataFrame:
    """A stream that reads the rows of ``df`` in batches, one file at a time."""
    path = fresh_path(spark, "replay")
    df.repartition(files).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream to its end into a Parquet table (or, for other modes, keep each key's last row) and read it."""
    spark = stream.sparkSession
    path, state = fresh_path(spark, "sink"), fresh_path(spark, "state")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
    else:
        def put(batch: DataFrame, n: int) -> None:
            batch.withColumn("_batch", F.lit(n)).write.mode("append").parquet(path)

        q = stream.writeStream.foreachBatch(put).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path)


def incremental_block(stream: DataFrame, block_batch) -> DataFrame:
    """Pairs of each micro-batch of ``(rec_id, text)`` against a frozen index; results are appended."""
    spark = stream.sparkSession
    path, state = fresh_path(spark, "pairs"), fresh_path(spark, "state")

    def put(batch: DataFrame, n: int) -> None:
        block_batch(batch).write.mode("append").parquet(path)

    stream.writeStream.foreachBatch(put).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(path)
