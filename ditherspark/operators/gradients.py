"""Gradient oracles over tables: exact values and gradients, and unbiased mini-batch gradients of logical workers.

Rows are (row_id, x array<double>, y) with dense ids 0..m-1, or (row_id, coord, y) for losses that touch one coordinate.
A logical worker is a draw slot or a hash of the row id, never a partition, so results don't depend on the cluster.
Sums are made in each task first and merged in the executors; the driver gets each number once.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.functions.rng import STREAMS, counter_hash, draw_indices, hash60
from ditherspark.operators.codec import listed
from ditherspark.operators.protocol import RunConfig, loss_factor, loss_value

#: Draws whose table is broadcast; more are joined by a shuffle.
BROADCAST_DRAWS = 1_000_000
#: Coordinates of one row of a partial sum.
BLOCK_SIZE = 4096
BLOCK = "block int, s array<double>"


def blocks(sums: np.ndarray):
    """A task's sums as rows (block, s) of ``BLOCK_SIZE`` numbers."""
    for i in range(0, len(sums), BLOCK_SIZE):
        yield pa.RecordBatch.from_arrays([pa.array([i // BLOCK_SIZE], pa.int32()), pa.array([sums[i : i + BLOCK_SIZE].tolist()], pa.list_(pa.float64()))], ["block", "s"])


def merged(parts: DataFrame) -> DataFrame:
    """(block, s) summed over all tasks: first by tasks of some dozens of partial sums each, then by block."""

    def some(batches):
        total: dict[int, np.ndarray] = {}
        for b in batches:
            for i, s in zip(b["block"].to_pylist(), b["s"], strict=True):
                v = s.values.to_numpy(zero_copy_only=False)
                total[i] = total[i] + v if i in total else v
        for i, v in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([v.tolist()], pa.list_(pa.float64()))], ["block", "s"])

    tasks = max(1, int(int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions")) ** 0.5))
    level = parts.repartition(tasks).mapInArrow(some, BLOCK)
    return level.repartition(tasks, "block").mapInArrow(some, BLOCK)


def collected(parts: DataFrame, size: int) -> np.ndarray:
    """The merged sums, ``size`` numbers, on the driver."""
    out = np.zeros(size)
    for r in merged(parts).collect():
        out[r["block"] * BLOCK_SIZE : r["block"] * BLOCK_SIZE + len(r["s"])] += r["s"]
    return out


class GradientOracle:
    """Values, gradients and worker gradients of a loss over dense rows."""

    sparse = False

    def __init__(self, rows: DataFrame, loss: str = "lsq", m: int | None = None):
        self.rows, self.loss, self._m = rows, loss, m

    @property
    def m(self) -> int:
        if self._m is None:
            self._m = self.rows.count()
        return self._m

    @staticmethod
    def dense(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
        x = batch["x"].flatten().to_numpy(zero_copy_only=False).reshape(-1, d) if batch.num_rows else np.zeros((0, d))
        return x, batch["y"].to_numpy(zero_copy_only=False).astype(np.float64)

    def columns(self) -> list[str]:
        return ["x", "y"]

    def evaluate(self, points: np.ndarray, gradients: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """(values, gradients) at the rows of ``points``, a stated set, in one pass over all rows."""
        d, kind, dense, n = points.shape[1], self.loss, self.dense, len(points)
        held = self.rows.sparkSession.sparkContext.broadcast(points)

        def run(batches):
            p, total, grad, rows = held.value, np.zeros(n), np.zeros((n, d) if gradients else (0, d)), 0
            for b in batches:
                for at in range(0, b.num_rows, 4096):
                    a, y = dense(b.slice(at, 4096), d)
                    z = a @ p.T
                    total += loss_value(kind, z, y[:, None]).sum(0)
                    if gradients:
                        grad += loss_factor(kind, z, y[:, None]).T @ a
                    rows += len(y)
            if rows:
                yield from blocks(np.concatenate([[rows], total, grad.ravel()]))

        parts = self.rows.select(*self.columns()).mapInArrow(run, BLOCK)
        sums = collected(parts, 1 + n + n * d * gradients)
        m = max(1.0, sums[0])
        return sums[1 : n + 1] / m, sums[n + 1 :].reshape(-1, d) / m

    def value(self, x: np.ndarray) -> float:
        return float(self.evaluate(np.asarray(x, float)[None])[0][0])

    def full_grad(self, x: np.ndarray) -> np.ndarray:
        return self.evaluate(np.asarray(x, float)[None], True)[1][0]

    def drawn(self, rounds: int, n: int, m_prime: int, seed: int = 0, first: int = 0) -> DataFrame:
        """Rows for every (t, worker, slot) of ``rounds`` rounds from ``first`` on, with replacement, uniformly over all
        rows."""
        draws = draw_indices(self.rows.sparkSession, rounds, n, m_prime, self.m, seed, first)
        if rounds * n * m_prime <= BROADCAST_DRAWS:
            draws = F.broadcast(draws)
        return self.rows.join(draws, "row_id")

    def partial_gradients(self, drawn: DataFrame, x: np.ndarray) -> DataFrame:
        """(worker, n, g): summed gradients of a task's rows for each worker."""
        d, kind, dense = len(x), self.loss, self.dense
        held = drawn.sparkSession.sparkContext.broadcast(np.asarray(x, float))

        def run(batches):
            ids, count, total = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, d))
            for b in (whole.slice(at, 4096) for whole in batches for at in range(0, whole.num_rows, 4096)):
                a, y = dense(b, d)
                g = loss_factor(kind, a @ held.value, y)[:, None] * a
                both, at = np.unique(np.concatenate([ids, b["worker"].to_numpy(zero_copy_only=False)]), return_inverse=True)
                new, n = np.zeros((len(both), d)), np.zeros(len(both), np.int64)
                np.add.at(new, at, np.concatenate([total, g]))
                np.add.at(n, at, np.concatenate([count, np.ones(len(g), np.int64)]))
                ids, count, total = both, n, new
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(count), listed(total)], ["worker", "n", "g"])

        return drawn.select("worker", *self.columns()).mapInArrow(run, "worker int, n bigint, g array<double>")

    def worker_gradients(self, x: np.ndarray, t: int, cfg: RunConfig, seed: int = 0) -> DataFrame:
        """(worker, g): the mini-batch gradient of each worker in round ``t``; only that round's draws are made."""
        return _averaged(self.partial_gradients(self.drawn(1, cfg.n_workers, cfg.m_prime, seed, t), x))


def _averaged(parts: DataFrame) -> DataFrame:
    """Means by worker: an exchange by worker, then one pass over each task's rows in their order."""

    def mean(group: pa.Table) -> pa.Table:
        column = group["g"].combine_chunks()
        g = column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).sum(axis=0) / group["n"].to_numpy().sum()
        return pa.table({"worker": group["worker"].slice(0, 1), "g": pa.array([g.tolist()], pa.list_(pa.float64()))})

    return parts.groupBy("worker").applyInArrow(mean, "worker int, g array<double>")


class ShardOracle(GradientOracle):
    """Each row belongs to one worker by a hash of its id; a worker's gradient is over all its rows. Workers are
    independent copies only in so far as rows are."""

    def worker_gradients(self, x, t, cfg, seed=0):
        dealt = self.rows.withColumn("worker", (hash60(seed, "shard", F.col("row_id")) % cfg.n_workers).cast("int"))
        return _averaged(self.partial_gradients(dealt, x))


class OneSparseOracle(GradientOracle):
    """f(x) = mean of (x[coord] - y)^2: every row touches one coordinate, every gradient has at most m' entries."""

    sparse = True

    def columns(self):
        return ["coord", "y"]

    @staticmethod
    def dense(batch, d):
        a = np.zeros((batch.num_rows, d))
        a[np.arange(batch.num_rows), batch["coord"].to_numpy(zero_copy_only=False)] = 1
        return a, batch["y"].to_numpy(zero_copy_only=False).astype(np.float64)

    def statistics(self, d: int) -> tuple[np.ndarray, np.ndarray, float]:
        """(rows, mean of y) by coordinate and the mean of y^2 left over: the exact minimiser and value, d rows."""
        r = self.rows.groupBy("coord").agg(F.count("*").alias("n"), F.avg("y").alias("mu"), F.sum(F.col("y") * F.col("y")).alias("s")).collect()
        n, mu, rest = np.zeros(d), np.zeros(d), 0.0
        for x in r:
            n[x["coord"]], mu[x["coord"]] = x["n"], x["mu"]
            rest += x["s"] - x["n"] * x["mu"] ** 2
        return n, mu, rest / max(1.0, n.sum())


class SparseOracle(GradientOracle):
    """Rows (row_id, coords array<int>, values array<double>, y): only what isn't zero is stored and shuffled; a slice of
    some thousand rows is made dense while it is worked on."""

    def columns(self):
        return ["coords", "values", "y"]

    @staticmethod
    def dense(batch, d):
        a = np.zeros((batch.num_rows, d))
        many = pc.list_value_length(batch["coords"]).to_numpy(zero_copy_only=False)
        at = np.repeat(np.arange(batch.num_rows), many)
        np.add.at(a, (at, batch["coords"].flatten().to_numpy(zero_copy_only=False)), batch["values"].flatten().to_numpy(zero_copy_only=False))
        return a, batch["y"].to_numpy(zero_copy_only=False).astype(np.float64)


class CoordOracle(GradientOracle):
    """d times one uniformly drawn partial derivative of the full gradient: unbiased and 1-sparse."""

    def worker_gradients(self, x, t, cfg, seed=0):
        spark, d = self.rows.sparkSession, len(x)
        held = spark.sparkContext.broadcast(self.full_grad(x))

        def run(batches):
            for b in batches:
                w = b["id"].to_numpy(zero_copy_only=False)
                i = (counter_hash(seed, STREAMS["coordinate"], t, w) % np.uint64(d)).astype(np.int64)
                out = np.zeros((len(w), d))
                out[np.arange(len(w)), i] = d * held.value[i]
                yield pa.RecordBatch.from_arrays([pa.array(w, pa.int32()), listed(out)], ["worker", "g"])

        return spark.range(cfg.n_workers).mapInArrow(run, "worker int, g array<double>")


def estimate_sigma2(oracle: GradientOracle, x: np.ndarray, m_prime: int, draws: int = 256, seed: int = 0) -> tuple[float, float]:
    """(mean squared deviation of mini-batch gradients from the full one, largest gradient norm) over ``draws`` draws."""
    cfg = RunConfig(d=len(x), n_workers=draws, m_prime=m_prime)
    full = oracle.full_grad(x)
    g = np.array([r["g"] for r in oracle.worker_gradients(x, 0, cfg, seed).collect()])
    return float(((g - full) ** 2).sum(1).mean()), float(np.linalg.norm(g, axis=1).max())
