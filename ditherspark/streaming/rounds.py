"""Descent over a stream: every micro-batch is one round, and its rows' hash deals them to logical workers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ditherspark.functions.rng import hash60
from ditherspark.operators.descent import RunResult, exists, server_mean
from ditherspark.operators.gradients import GradientOracle, OneSparseOracle, _averaged
from ditherspark.operators.protocol import RunConfig, send_down


def batch_round(rows: DataFrame, x: np.ndarray, cfg: RunConfig, t: int, seed: int = 0, oracle: type[GradientOracle] = OneSparseOracle) -> np.ndarray:
    """The iterate after one round on ``rows`` (row_id, coord, y)."""
    o = oracle(rows, cfg.loss)
    dealt = rows.withColumn("worker", (hash60(seed, "shard", F.col("row_id")) % cfg.n_workers).cast("int"))
    w, _, _ = server_mean(_averaged(o.partial_gradients(dealt, x)), cfg, t, seed)
    v, _ = send_down(w, cfg, t, seed)
    return x - cfg.step(t) * v[: cfg.d]


STATE = "t bigint, x array<double>"


def stored_state(spark: SparkSession, path: str, before: int | None = None) -> tuple[int, list[float]] | None:
    """(t, iterate after it) of the last stored round, or of the last one before ``before``."""
    if not exists(spark, path):
        return None
    rows = spark.read.schema(STATE).parquet(path)
    rows = rows if before is None else rows.where(F.col("t") < before)
    got = rows.agg(F.max_by(F.struct("t", "x"), "t").alias("s")).first()["s"]
    return (got["t"], list(got["x"])) if got else None


def rounds_from_stream(stream: DataFrame, cfg: RunConfig, checkpoint: str, seed: int = 0) -> RunResult:
    """Runs until the stream has no more data. Iterates are stored beside the checkpoint, a row a round, so a run that
    starts again goes on from the last one, and a batch that is run again starts from the round before it and gives the
    same messages."""
    spark, path = stream.sparkSession, f"{checkpoint.rstrip('/')}/iterates"

    def one(batch: DataFrame, t: int) -> None:
        if not batch.isEmpty():
            held = stored_state(batch.sparkSession, path, t)
            x = batch_round(batch, np.array(held[1]) if held else np.zeros(cfg.d), cfg, t, seed)
            row = batch.sparkSession.createDataFrame([(t, x.tolist())], STATE)
            row.coalesce(1).write.mode("overwrite").parquet(f"{path}/batch={t}")

    query = stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{checkpoint.rstrip('/')}/offsets").trigger(availableNow=True).start()
    query.awaitTermination()
    if not exists(spark, path):
        return RunResult(np.zeros(cfg.d), np.zeros(cfg.d))
    rows = spark.read.schema(STATE).parquet(path).select("t", "x").orderBy("t").collect()  # a row a round
    trace = [{"t": r["t"], "x": np.array(r["x"])} for r in rows]
    return RunResult(trace[-1]["x"], trace[-1]["x"], trace)


def running_means(stream: DataFrame, delay: str = "10 minutes", window: str = "1 hour") -> DataFrame:
    """Count and mean by coordinate and window of event time (the exact minimiser of each window); rows later than
    ``delay`` are dropped. ``ts`` must be a timestamp with zone."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", window), "coord").agg(F.count("*").alias("n"), F.avg("y").alias("mu"))
