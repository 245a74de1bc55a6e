"""Runners of the descent recursion, with one set of kernels.

``descend`` is the distributed runner. A round draws its rows, sums gradients in each task, averages them by worker (first
exchange) and packs each worker's message there. Messages, bytes and nothing else, go through an exchange to the tasks
that play the server's front: they unpack, decode and sum, and count the bytes that arrived. Sums are merged by blocks
of coordinates, so the driver gets d numbers once; it packs the server's message and steps with what unpacking that
gives. The plan doesn't grow with the rounds, as the iterate enters by broadcast and only the round's draws are made, and
the runner can write its state to the shared folder and resume.

``trajectories`` is the seed-parallel runner for expectations: the rows of all draws are fetched once, and a whole run
of a small-d problem is one group, so many (method, seed) pairs run at once.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ditherspark.operators.codec import bytes_of, packed_column
from ditherspark.operators.gradients import BLOCK, GradientOracle, blocks, collected
from ditherspark.operators.protocol import RunConfig, encode_up, loss_factor, pack_down, pack_up, send_down, send_up, traffic, unpack_down, unpack_up

TRACE = "run string, seed int, t int, delta double, x array<double>, v_sq double, dev_server double, dev_worker double, half_space double, worker_clips int, server_clip boolean, bits_up double, bits_down double, inner double, top_grad double, dev_total double, cross double"


#: Drawn numbers (rounds x workers x m' x d) that a run of the seed-parallel runner may hold in its task: 1 GB.
GROUP_NUMBERS = 1 << 27


@dataclass
class RunResult:
    x_last: np.ndarray
    x_avg: np.ndarray
    trace: list[dict] = field(default_factory=list)


def exists(spark: SparkSession, path: str) -> bool:
    """Whether a path is there, in any store that Spark reads."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def project(x: np.ndarray, radius: float) -> np.ndarray:
    norm = np.linalg.norm(x)
    return x * (radius / norm) if radius and norm > radius else x


def average_iterate(xs: np.ndarray, deltas: np.ndarray) -> np.ndarray:
    """Mean of the iterates, weighted by their steps."""
    return (np.asarray(deltas)[:, None] * xs).sum(0) / np.sum(deltas)


MESSAGE_UP = "worker int, packed binary, eps binary, clipped boolean"


def worker_messages(grads: DataFrame, cfg: RunConfig, t: int, seed: int) -> DataFrame:
    """(worker, packed, eps, clipped) of gradients (worker, g): what workers send, and whether they clipped (an audit)."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            g = b["g"].flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            up = encode_up(g, b["worker"].to_numpy(zero_copy_only=False), cfg, t, seed)
            packed, eps = pack_up(up, cfg)
            yield pa.RecordBatch.from_arrays([b["worker"], packed_column(packed), packed_column(eps), pa.array(up.clipped)], ["worker", "packed", "eps", "clipped"])

    return grads.mapInArrow(run, MESSAGE_UP)


def server_sums(messages: DataFrame, cfg: RunConfig) -> DataFrame:
    """Partial sums (block, s) of what arrives: workers, clips, bytes, then the decoded coordinates. Messages are dealt by
    worker to at most a shuffle's partitions."""

    def run(batches):
        total, seen = np.zeros(cfg.width), np.zeros(3)
        for b in batches:
            if not b.num_rows:
                continue
            packed, eps = bytes_of(b["packed"]), bytes_of(b["eps"])
            total += unpack_up(packed, eps, cfg).sum(0)
            seen += (len(packed), pc.sum(b["clipped"].cast(pa.int64())).as_py(), packed.size + eps.size)
        if seen[0]:
            yield from blocks(np.concatenate([seen, total]))

    tasks = min(cfg.n_workers, int(messages.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return messages.repartition(tasks, "worker").mapInArrow(run, BLOCK)


def server_mean(grads: DataFrame, cfg: RunConfig, t: int, seed: int) -> tuple[np.ndarray, int, int]:
    """(mean of the decoded messages, clips, bits that arrived)."""
    sums = collected(server_sums(worker_messages(grads, cfg, t, seed), cfg), 3 + cfg.width)
    return sums[3:] / sums[0], int(sums[1]), 8 * int(sums[2])


def descend(oracle: GradientOracle, cfg: RunConfig, seed: int = 0, x0: np.ndarray | None = None, state_path: str | None = None) -> RunResult:
    """Runs ``cfg.rounds`` rounds; with ``state_path`` (JSON lines, written by Spark) it goes on from the last one there."""
    spark = oracle.rows.sparkSession
    x, first, weighted, weight = (np.zeros(cfg.d) if x0 is None else np.asarray(x0, float)), 0, np.zeros(cfg.d), 0.0
    if state_path:
        if exists(spark, state_path):
            s = json.loads(spark.read.text(state_path).orderBy(F.get_json_object("value", "$.t").cast("int").desc()).first()[0])
            x, first, weighted, weight = np.array(s["x"]), s["t"], np.array(s["weighted"]), s["weight"]
    out = RunResult(x, x)
    for t in range(first, cfg.rounds):
        delta = cfg.step(t)
        weighted, weight = weighted + delta * x, weight + delta
        w, clips, up = server_mean(oracle.worker_gradients(x, t, cfg, seed), cfg, t, seed)
        message, clip = pack_down(w, cfg, t, seed)
        v = unpack_down(message, cfg)
        out.trace.append({"t": t, "delta": delta, "x": x.copy(), "v": v[: cfg.d].copy(), "w": w[: cfg.d].copy(), "worker_clips": clips, "server_clip": clip, "bits_up": up, "bits_down": 8 * len(message)})
        x = project(x - delta * v[: cfg.d], cfg.radius)
        if state_path:
            state = {"t": t + 1, "x": x.tolist(), "weighted": weighted.tolist(), "weight": weight}
            spark.createDataFrame([(json.dumps(state),)], "value string").coalesce(1).write.mode("append").text(state_path)
    out.x_last, out.x_avg = x, weighted / weight if weight else x
    return out


def _run(name: str, seed: int, cfg: RunConfig, a: np.ndarray, y: np.ndarray, x_star: np.ndarray | None, every: int) -> pd.DataFrame:
    """A whole run on drawn rows ``a`` (rounds, workers, m', d) and ``y``; the last row of the trace is the average iterate."""
    x, rows, xs, deltas = np.zeros(cfg.d), [], [], []
    up, down = traffic(cfg)
    workers = np.arange(cfg.n_workers)
    star = np.zeros(cfg.d) if x_star is None else x_star
    for t in range(cfg.rounds):
        delta = cfg.step(t)
        g = (loss_factor(cfg.loss, a[t] @ x, y[t])[:, :, None] * a[t]).mean(axis=1)
        got, clipped = send_up(g, workers, cfg, t, seed)
        w = got.sum(0) / cfg.n_workers
        v, clip = send_down(w, cfg, t, seed)
        xs.append(x.copy())
        deltas.append(delta)
        if t % every == 0 or t == cfg.rounds - 1:
            wd, vd = w[: cfg.d], v[: cfg.d]
            rows.append((name, seed, t, delta, x.tolist(), float(vd @ vd), float(((vd - wd) ** 2).sum()), float(((wd - g.mean(0)) ** 2).sum()), float(vd.sum()), int(clipped.sum()), clip, up, down, float((x - star) @ vd), float(np.linalg.norm(g, axis=1).max()), float(((vd - g.mean(0)) ** 2).sum()), float((x - star) @ (g.mean(0) - vd))))
        x = project(x - delta * v[: cfg.d], cfg.radius)
    mean = average_iterate(np.array(xs), np.array(deltas))
    rows.append((name, seed, cfg.rounds, float(np.sum(deltas)), mean.tolist(), 0.0, 0.0, 0.0, 0.0, 0, False, up * cfg.rounds, down * cfg.rounds, 0.0, 0.0, 0.0, 0.0))
    return pd.DataFrame(rows, columns=[c.split()[0] for c in TRACE.split(", ")])


def trajectories(oracle: GradientOracle, runs: dict[str, RunConfig], seeds: int = 1, x_star: np.ndarray | None = None, every: int = 1) -> DataFrame:
    """The trace of every run and seed; the row with t = rounds holds the average iterate and the run's whole traffic.
    The runs of one call share their shape (rounds, workers, m'), and thus their draws."""
    shapes = {(c.rounds, c.n_workers, c.m_prime) for c in runs.values()}
    if len(shapes) != 1:
        raise ValueError("runs of one call must have the same rounds, workers and m'")
    rounds, n, mp = shapes.pop()
    cols, d = oracle.columns(), next(iter(runs.values())).d
    drawn = None
    for s in range(seeds):
        part = oracle.drawn(rounds, n, mp, s).select(F.lit(s).alias("seed"), "t", "worker", "slot", *cols)
        drawn = part if drawn is None else drawn.union(part)
    held = {k: asdict(c) for k, c in runs.items()}
    dense = oracle.dense

    def group(key, pdf: pd.DataFrame) -> pd.DataFrame:
        name, seed = key
        cfg = RunConfig(**held[name])
        pdf = pdf.sort_values(["t", "worker", "slot"])
        a, y = dense(pa.RecordBatch.from_pandas(pdf[cols], preserve_index=False), d)
        return _run(name, int(seed), cfg, a.reshape(rounds, n, mp, d), y.reshape(rounds, n, mp), x_star, every)

    held_numbers = rounds * n * mp * d
    if held_numbers > GROUP_NUMBERS:
        raise ValueError(f"a run of {held_numbers} drawn numbers is for descend, not for one task")
    pairs = drawn.withColumn("run", F.explode(F.array(*[F.lit(k) for k in runs])))
    return pairs.groupBy("run", "seed").applyInPandas(group, TRACE)


def telescoping(trace: DataFrame, x_star: np.ndarray) -> DataFrame:
    """For each run and seed the slack of sum(delta <x_t - x*, v_t>) <= (||x* - x_0||^2 + sum(delta^2 ||v_t||^2)) / 2, which
    holds for any directions; needs every round."""
    last = F.max("t").over(Window.partitionBy("run", "seed"))
    rows = trace.withColumn("last", last).where(F.col("t") < F.col("last"))
    start = float((x_star**2).sum())
    left = F.sum(F.col("delta") * F.col("inner"))
    right = F.lit(start / 2) + F.sum(F.col("delta") ** 2 * F.col("v_sq")) / 2
    return rows.groupBy("run", "seed").agg(left.alias("progress"), right.alias("allowed"), (right - left).alias("slack"))
