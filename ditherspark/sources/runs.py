"""Stored runs: traces and messages as Parquet, a folder a run, so that a reader of one run touches no other."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_trace(trace: DataFrame, path: str) -> None:
    """Appends rows of ``trace`` below ``path``/run=..."""
    trace.write.mode("append").partitionBy("run").parquet(path)


def read_trace(spark: SparkSession, path: str, run: str | None = None) -> DataFrame:
    """All runs, or one, of which only its folder is read."""
    df = spark.read.parquet(path)
    return df.where(F.col("run") == run) if run else df


def write_messages(messages: DataFrame, path: str, buckets: int = 16) -> None:
    """Messages by a hash of their id, some ``buckets`` files."""
    messages.repartition(buckets, "id").write.mode("overwrite").parquet(path)


def write_stream(trace: DataFrame, path: str, checkpoint: str):
    """A streaming sink for traces: each batch once."""
    return trace.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
