"""Accuracy measures of the quantizer, the codec and runs, each beside its exact value or bound."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ditherspark.functions import closed_forms as C
from ditherspark.functions.rng import stream
from ditherspark.operators.codec import decode_rows, encode_rows, padded, vectors
from ditherspark.operators.gradients import GradientOracle
from ditherspark.operators.quantize import dither_quantize


def roundtrip_table(df: DataFrame, configs: list[tuple[str, float, int]], d: int = 64, seeds: int = 20) -> DataFrame:
    """A row for each (basis, alpha, K): mean squared error of unit vectors against the value without clipping and the
    bound; clip share against its bound; outputs over the norm cap lam * sqrt(d) (never). One scan, and one transform for
    each basis, serve all of them."""
    lams = [C.amplitudes(a, 1.0, 1.0, d)[0] for _, a, _ in configs]

    def run(batches):
        for b in batches:
            x, _ = vectors(b["v"], d)
            ids, norm = b["id"].to_numpy(zero_copy_only=False), (x * x).sum(1)
            for s in range(seeds):
                for i, (basis, _, k) in enumerate(configs):
                    q, eps, z = encode_rows(x, ids, lams[i], k, s, basis=basis)
                    y, top = decode_rows(q, eps, lams[i], k, basis), np.abs(z).max(1) if len(z) else np.zeros(0)
                    cols = [np.full(len(ids), i), ((y - x) ** 2).sum(1), (y * y).sum(1), top, norm]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["config", "err_sq", "out_sq", "top", "norm_sq"])

    src = df.selectExpr("cast(vec_id as bigint) id", "cast(embedding as array<double>) v")
    r = src.mapInArrow(run, "config bigint, err_sq double, out_sq double, top double, norm_sq double")
    about = [(i, basis, a, k, lam, d * (2 if basis == "fourier" else 1), C.roundtrip_mse_bound(a, 1.0, d, k), C.flatness_failure(a, d)) for i, ((basis, a, k), lam) in enumerate(zip(configs, lams, strict=True))]
    about = df.sparkSession.createDataFrame(about, "config bigint, basis string, alpha double, k int, lam double, size int, bound double, clip_bound double")
    r = r.join(F.broadcast(about), "config")
    return r.groupBy("basis", "alpha", "k", "lam", "size", "bound", "clip_bound").agg(
        F.count("*").alias("n"), F.avg("err_sq").alias("mse"), (F.stddev("err_sq") / F.sqrt(F.count("*"))).alias("std_error"),
        ((F.lit(d) * F.col("lam") * F.col("lam") - F.avg("norm_sq") * d / F.col("size")) / F.col("k")).alias("exact"),
        F.avg((F.col("top") > F.col("lam")).cast("double")).alias("clip_share"), F.avg(F.col("top") / F.sqrt("norm_sq")).alias("top_entry"),
        F.sum((F.sqrt("out_sq") > F.col("lam") * F.sqrt("size") * (1 + 1e-9)).cast("long")).alias("over_cap"),
    ).drop("lam", "size")


def roundtrip_mse(df: DataFrame, alpha: float, k: int, d: int = 64, seeds: int = 20, basis: str = "butterfly") -> DataFrame:
    """``roundtrip_table`` of one configuration."""
    return roundtrip_table(df, [(basis, alpha, k)], d, seeds)


def sampled_moments(df: DataFrame, lam: float, draws: int = 400, id_col: str = "vec_id", col: str = "embedding") -> DataFrame:
    """Per vector y, with x its reverse and A two rows of signs times x: sampled and exact second moment of <x, Q(y)>, and
    matrix error of Q(y)."""

    def run(batches):
        for b in batches:
            y, ids = padded(b["v"].to_pylist()), np.array(b["id"].to_pylist())
            rows = []
            for i, v in zip(ids, y, strict=True):
                x = v[::-1].copy()
                a = np.stack([x, x * (1 - 2 * (np.arange(len(x)) % 2))])
                q = dither_quantize(np.repeat(v[None], draws, 0), lam, 1, stream(0, "moments", int(i)))
                rows.append((i, ((q @ x) ** 2).mean(), C.inner_second_moment(x, v, lam), (((q - v) @ a.T) ** 2).sum(1).mean(), C.matrix_quant_error(a, v, lam)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64()] + [pa.float64()] * 4, strict=True)], ["id", "inner_sampled", "inner_exact", "matrix_sampled", "matrix_exact"])

    src = df.selectExpr(f"cast({id_col} as bigint) id", f"cast({col} as array<double>) v")
    return src.mapInArrow(run, "id bigint, inner_sampled double, inner_exact double, matrix_sampled double, matrix_exact double")


def mean_roundtrip(df: DataFrame, n: int, alpha: float = 3.0, d: int = 64, seeds: int = 20, shared: bool = False) -> DataFrame:
    """(deviation of the mean of n decoded vectors, exact without clipping, bound, cross terms) averaged over groups of n
    and seeds: errors of different workers are uncorrelated, so the deviation falls as 1/n. Vectors are dealt to groups by
    dense numbers, and those left over (fewer than n) count in ``left_over``, as a smaller group has another bound."""
    lam, _ = C.amplitudes(alpha, 1.0, 1.0, d)
    scope = "round" if shared else "worker"

    def group(key, pdf):
        x, ids = padded(list(pdf["v"])), pdf["id"].to_numpy()
        out = []
        for s in range(seeds):
            q, eps, _ = encode_rows(x, ids, lam, 1, s, int(key[0]), "worker", "butterfly", scope)
            e = decode_rows(q, eps, lam, 1) - x
            each, mean = (e * e).sum(1), e.mean(0)
            out.append((len(x), (mean * mean).sum(), each.mean() / len(x), (mean * mean).sum() - each.sum() / len(x) ** 2))
        import pandas as pd

        return pd.DataFrame(out, columns=["n", "dev", "independent", "cross"])

    buckets = F.pmod(F.xxhash64("vec_id"), F.lit(max(1, df.count() // (16 * n)))).alias("b")  # some 16 groups a bucket
    place = F.row_number().over(Window.partitionBy("b").orderBy("id")) - 1
    src = df.selectExpr("cast(vec_id as bigint) id", "cast(embedding as array<double>) v", "vec_id").select("id", "v", buckets)
    src = src.withColumn("g", F.shiftleft("b", 32) + F.floor(place / n))
    r = src.select("id", "v", "g").groupBy("g").applyInPandas(group, "n bigint, dev double, independent double, cross double")
    left = F.sum(F.when(F.col("n") < n, F.col("n") / seeds).otherwise(0)).cast("long").alias("left_over")
    full = lambda c: F.when(F.col("n") == n, F.col(c))
    bound = C.mean_roundtrip_mse_bound(alpha, 1.0, d, n)
    count = F.count(full("dev"))
    return r.agg(F.lit(n).alias("workers"), count.alias("samples"), F.avg(full("dev")).alias("deviation"), F.avg(full("independent")).alias("if_uncorrelated"), F.avg(full("cross")).alias("cross_terms"), (F.stddev(full("cross")) / F.sqrt(count)).alias("cross_std_error"), F.lit(bound).alias("bound"), left)


def round_deviation(trace: DataFrame, alpha: float, alpha_s: float, bound: float, d: int, n: int, k: int) -> DataFrame:
    """One-round mean squares against their bounds, and clips, by run."""
    first, second = C.round_deviation_bounds(alpha, alpha_s, bound, d, n, k)
    rows = trace.where("bits_up > 0 AND top_grad > 0")
    return rows.groupBy("run").agg(
        F.count("*").alias("rounds"), F.avg("dev_worker").alias("worker_deviation"), F.lit(first).alias("worker_bound"), F.avg("dev_server").alias("server_deviation"), F.lit(second).alias("server_bound"),
        F.sum("worker_clips").alias("worker_clips"), F.sum((F.col("worker_clips") > 0).cast("long")).alias("rounds_with_clip"), F.sum(F.col("server_clip").cast("long")).alias("server_clips"),
        F.lit(n * C.flatness_failure(alpha, d)).alias("clip_bound_round"), F.max("top_grad").alias("top_grad"),
    )


def with_objective(trace: DataFrame, oracle: GradientOracle, gradients: bool = True) -> DataFrame:
    """``trace`` with f and the squared gradient norm at every iterate in it: one pass over the table for all of them."""
    trace = trace.orderBy("run", "seed", "t").toArrow()  # the audited rounds
    points = trace["x"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(trace.num_rows, -1)
    f, g = oracle.evaluate(points, gradients)
    sq = (g * g).sum(1) if gradients else np.zeros(len(f))
    return oracle.rows.sparkSession.createDataFrame(trace.append_column("f", pa.array(f)).append_column("grad_sq", pa.array(sq)))


def smoothness_violations(oracle: GradientOracle, points: np.ndarray, smooth: float) -> list[tuple[float, float, bool]]:
    """(f(q), its quadratic limit from p, violated) for neighbouring points."""
    f, g = oracle.evaluate(points, True)
    out = []
    for i in range(len(points) - 1):
        step = points[i + 1] - points[i]
        limit = f[i] + float(g[i] @ step) + smooth / 2 * float(step @ step)
        out.append((float(f[i + 1]), float(limit), bool(f[i + 1] > limit + 1e-12)))
    return out


def min_ratio(alpha: float, d: int) -> float:
    """alpha over the value from which the bounds' hypothesis holds; below 1 a run is a demonstration only."""
    return alpha / C.min_alpha(d) if d > 1 else math.nan
