"""Workloads whose results are statistics or runs; tests hold them against bounds, exact values or replays."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ditherspark.functions import closed_forms as C
from ditherspark.functions.rng import hash60
from ditherspark.operators import measures
from ditherspark.operators.descent import descend, telescoping, trajectories
from ditherspark.operators.gradients import CoordOracle, GradientOracle, OneSparseOracle, ShardOracle, SparseOracle, estimate_sigma2
from ditherspark.operators.protocol import RunConfig, method
from ditherspark.operators.wide import to_blocks, wide_butterfly, wide_long
from ditherspark.plans.portable import EVENT_D, event_rows, hashed_words
from ditherspark.sources.tables import load, shared_folder

QUERIES, ORACLES = {}, {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def _embeddings(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "embeddings", "vec_id", "embedding")


def planted() -> np.ndarray:
    """The hidden direction of the planted labels."""
    from ditherspark.functions.rng import hash60_py

    x = np.array([hash60_py(0, "plant", c) % 2001 - 1000 for c in range(64)], float)
    return 4 * x / np.linalg.norm(x)


def planted_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, x, y): unit vectors labelled by the side of a hidden plane, one in twenty flipped."""
    hidden = F.array(*[F.lit(float(v)) for v in planted()])
    x = F.transform("embedding", lambda v: v.cast("double"))
    side = F.aggregate(F.zip_with(x, hidden, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    flip = F.when(hash60(0, "flip", F.col("vec_id")) % 20 == 0, -1.0).otherwise(1.0)
    return _embeddings(spark, sf_dir).select(F.col("vec_id").alias("row_id"), x.alias("x"), (F.when(side >= 0, 1.0).otherwise(-1.0) * flip).alias("y"))


def numbered(rows: DataFrame, id_col: str, per_bucket: int = 100_000) -> tuple[DataFrame, int]:
    """(``rows`` with dense numbers ``row_id`` in place of the id, their count): places within hash buckets, whose number
    follows the rows, after the buckets before."""
    from pyspark.sql import Window

    buckets = max(1, -(-rows.count() // per_bucket))
    dealt = rows.withColumn("bucket", F.pmod(F.xxhash64(id_col), F.lit(buckets)))
    sizes = dealt.groupBy("bucket").agg(F.count("*").alias("n"))  # a row a bucket
    first = sizes.select("bucket", "n", (F.sum("n").over(Window.orderBy("bucket")) - F.col("n")).alias("first"))
    place = F.row_number().over(Window.partitionBy("bucket").orderBy(id_col)) - 1
    out = dealt.withColumn("place", place).join(F.broadcast(first.drop("n")), "bucket").withColumn("row_id", (F.col("place") + F.col("first")).cast("long"))
    return out.drop("bucket", "place", "first", id_col), int(sizes.agg(F.sum("n")).first()[0] or 0)


def _stack(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# Quantizer and codec.
@query
def inner_moment_table(spark, sf_dir):
    m = measures.sampled_moments(_embeddings(spark, sf_dir), 0.51)
    return m.agg(F.count("*").alias("n"), F.avg("inner_sampled").alias("sampled"), F.avg("inner_exact").alias("exact"))


@query
def matrix_error_table(spark, sf_dir):
    m = measures.sampled_moments(_embeddings(spark, sf_dir), 0.51)
    return m.agg(F.count("*").alias("n"), F.avg("matrix_sampled").alias("sampled"), F.avg("matrix_exact").alias("exact"))


@query
def mean_roundtrip_table(spark, sf_dir):
    """Deviation of the workers' mean against 1/N, with own and with shared signs."""
    df = _embeddings(spark, sf_dir)
    parts = [measures.mean_roundtrip(df, n, shared=s).withColumn("shared_sign", F.lit(s)) for n in (4, 16, 64) for s in (False, True)]
    return _stack(parts)


WIDE_SQL = """
WITH v AS (SELECT event_id % 4096 AS c, sum(CAST(floor(value * 100) AS BIGINT)) AS x FROM events GROUP BY 1)
SELECT k AS coord, CAST(sum(x * (1 - 2 * (bit_count(k & c) % 2))) AS BIGINT) AS z FROM v, (SELECT unnest(range(4096)) AS k) GROUP BY k
"""


@query
def wide_transform(spark, sf_dir):
    """The transform of a 4,096-vector in 64 blocks by one transpose; checked against the dense form."""
    e = load(spark, sf_dir, "events", "event_id", "value")
    long = e.select((F.col("event_id") % 4096).alias("coord"), F.floor(F.col("value") * 100).alias("x"))
    return wide_long(wide_butterfly(to_blocks(long, 6), 6, 6), 6)


ORACLES["wide_transform"] = WIDE_SQL


# Runs on 1-sparse events.
def _events(spark, sf_dir):
    o = OneSparseOracle(event_rows(spark, sf_dir))
    n, mu, rest = o.statistics(EVENT_D)
    return o, n / n.sum(), mu, rest


def _event_gaps(trace: DataFrame, p: np.ndarray, mu: np.ndarray) -> DataFrame:
    """Gap of each iterate out of the exact per-coordinate statistics, beside the floor of sign methods."""
    arr = lambda v: F.array(*[F.lit(float(x)) for x in v])
    sq = F.zip_with("x", arr(mu), lambda a, b: (a - b) * (a - b))
    gap = F.aggregate(F.zip_with(sq, arr(p), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    floor = float(mu.sum() ** 2 / (1 / p).sum())
    return trace.select("run", "seed", "t", gap.alias("gap"), F.lit(floor).alias("sign_floor"), "half_space", "worker_clips", "server_clip", "bits_up", "bits_down")


@query
def events_methods(spark, sf_dir):
    """Gaps of all methods on 1-sparse gradients (one draw a worker): sign methods stay above the floor."""
    o, p, mu, _ = _events(spark, sf_dir)
    base = RunConfig(d=EVENT_D, n_workers=64, rounds=150, delta=0.1, bound=12.0)
    runs = {m: method(m, base) for m in ("plain", "observed", "up_only", "vote", "sign_mean", "no_flatten", "no_dither", "random_k", "ternary")}
    return _event_gaps(trajectories(o, runs, every=30), p, mu)


@query
def onebit_events_gap(spark, sf_dir):
    """Two-way one-bit descent with the observed server amplitude goes below the floor of sign methods."""
    o, p, mu, _ = _events(spark, sf_dir)
    cfg = method("observed", RunConfig(d=EVENT_D, n_workers=1024, rounds=200, delta=0.1, bound=12.0))
    return _event_gaps(trajectories(o, {"observed": cfg}, every=100), p, mu)


@query
def onebit_events_gap_theorem(spark, sf_dir):
    """The same with the amplitude rule, which needs many rounds at a small step."""
    o, p, mu, _ = _events(spark, sf_dir)
    cfg = method("onebit", RunConfig(d=EVENT_D, n_workers=16, rounds=20_000, delta=0.01, bound=12.0))
    return _event_gaps(trajectories(o, {"onebit": cfg}, every=5000), p, mu)


@query
def param_sweep(spark, sf_dir):
    """Gap over K, alpha, step and N: more dithers, more workers and smaller steps help, a larger alpha costs."""
    o, p, mu, _ = _events(spark, sf_dir)
    out = []
    for n in (16, 64, 256):
        runs = {}
        for k in (1, 15, 255):
            for alpha in (2.0, 3.0):
                for delta in (0.02, 0.1):
                    runs[f"N={n} K={k} alpha={alpha} delta={delta}"] = method("observed", RunConfig(d=EVENT_D, n_workers=n, rounds=100, k=k, alpha=alpha, delta=delta, bound=12.0))
        out.append(_event_gaps(trajectories(o, runs, every=100), p, mu).where("t = 100"))
    return _stack(out)


@query
def trace_telescoping(spark, sf_dir):
    """The slack of the telescoping inequality, for every method and any directions."""
    o, _, mu, _ = _events(spark, sf_dir)
    base = RunConfig(d=EVENT_D, n_workers=32, rounds=60, delta=0.05, bound=12.0)
    return telescoping(trajectories(o, {m: method(m, base) for m in ("plain", "onebit", "up_only", "down_only", "vote", "sign_mean")}, x_star=mu), mu)


@query
def general_bound_table(spark, sf_dir):
    """Mean gap of the average iterate over seeds against the bound for any worker and server maps, whose last two terms
    come from the runs' own deviations and inner products."""
    o, p, mu, _ = _events(spark, sf_dir)
    n, rounds, delta = 32, 60, 0.05
    base = RunConfig(d=EVENT_D, n_workers=n, rounds=rounds, delta=delta, bound=12.0)
    t = trajectories(o, {m: method(m, base) for m in ("plain", "onebit", "observed", "up_only", "down_only")}, seeds=6, x_star=mu)
    arr = lambda v: F.array(*[F.lit(float(x)) for x in v])
    off = F.zip_with("x", arr(mu), lambda a, b: (a - b) * (a - b))
    weigh = lambda w: F.aggregate(F.zip_with(off, arr(w), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    sigma = estimate_sigma2(o, np.zeros(EVENT_D), 1)[0]
    runs = t.where(F.col("t") < rounds).groupBy("run").agg(F.avg(weigh(4 * p * p)).alias("grad_sq"), F.avg("dev_total").alias("dev"), F.avg("cross").alias("cross"))
    gaps = t.where(F.col("t") == rounds).groupBy("run").agg(F.avg(weigh(p)).alias("gap"))
    out = []
    for r in runs.join(gaps, "run").orderBy("run").collect():
        plain = C.bound_plain(float(mu @ mu), [delta] * rounds, [r["grad_sq"]] * rounds, sigma, n)
        terms = C.bound_general(plain, [delta] * rounds, [r["dev"]] * rounds, [r["cross"]] * rounds)
        out.append((r["run"], r["gap"], float(sum(terms.values())), *map(float, terms.values())))
    return spark.createDataFrame(out, "run string, gap double, bound double, start double, gradient double, variance double, deviation double, drift double")


@query
def single_node(spark, sf_dir):
    """One worker without compression, three step schedules."""
    o, p, mu, _ = _events(spark, sf_dir)
    base = method("local", RunConfig(d=EVENT_D, m_prime=4, rounds=120, delta=0.2))
    from dataclasses import replace

    runs = {"constant": base, "inverse root": replace(base, schedule="inv_sqrt"), "list": replace(base, schedule=tuple(0.5 / (1 + t / 10) for t in range(120)))}
    return _event_gaps(trajectories(o, runs, every=60), p, mu)


@query
def trace_average_iterate(spark, sf_dir):
    """The weighted mean of stored iterates, recomputed from the trace, against the one the run kept."""
    o, _, _, _ = _events(spark, sf_dir)
    cfg = method("plain", RunConfig(d=EVENT_D, n_workers=16, rounds=40, schedule="inv_sqrt"))
    t = trajectories(o, {"plain": cfg})
    xs = t.select("t", "delta", F.posexplode("x").alias("coord", "v"))
    mean = xs.where("t < 40").groupBy("coord").agg((F.sum(F.col("delta") * F.col("v")) / F.sum("delta")).alias("recomputed"))
    return mean.join(xs.where("t = 40").select("coord", F.col("v").alias("kept")), "coord")


# Runs on planted embeddings.
def _logistic(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
        cfg = method(name, RunConfig(d=64, n_workers=64, m_prime=1, rounds=150, delta=0.5 if name not in ("vote", "sign_mean") else 0.05, alpha=2.6, alpha_s=2.6, loss="logistic", server_amp="observed"))
        t = trajectories(o, {name: cfg}, every=50)
        return measures.with_objective(t, o).select("run", "seed", "t", "f", "grad_sq", "dev_worker", "dev_server", "worker_clips", "server_clip", "bits_up", "bits_down")

    run.__name__ = f"logistic_embed_{name}"
    run.__doc__ = f"Loss of {name} on the planted problem; the last row is the average iterate."
    return run


for _name in ("plain", "onebit", "up_only", "down_only", "vote", "sign_mean", "no_flatten", "no_dither", "shared_sign", "fourier", "cosine", "random_k", "ternary"):
    query(_logistic(_name))


@query
def logistic_bound(spark, sf_dir):
    """Measured gap (at most the loss, which is positive) against every term of the two-way bound, alpha at its minimum."""
    o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
    d, n, k, delta, alpha = 64, 16, 255, 0.02, C.min_alpha(64)
    cfg = method("onebit", RunConfig(d=d, n_workers=n, m_prime=4, k=k, rounds=100, delta=delta, alpha=alpha, alpha_s=alpha, loss="logistic"))
    t = measures.with_objective(trajectories(o, {"onebit": cfg}, seeds=2, every=1), o)
    star = planted()
    rows = t.where("t < 100").groupBy("seed").agg(F.avg("grad_sq").alias("g"), F.avg(F.sqrt(F.aggregate(F.zip_with("x", F.array(*map(F.lit, star.tolist())), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v))).alias("eta"))
    got = rows.join(t.where("t = 100").select("seed", "f"), "seed").collect()
    out = []
    for r in got:
        terms = C.bound_compressed(C.bound_plain(float(star @ star), [delta] * 100, [r["g"]] * 100, 1.0, n), alpha, alpha, 1.0, d, n, k, delta, r["eta"])
        out.append((r["seed"], r["f"], float(sum(terms.values())), *map(float, terms.values())))
    return spark.createDataFrame(out, "seed int, gap_at_most double, bound double, start double, gradient double, variance double, worker_share double, server_share double, clip_sq double, clip_distance double")


@query
def round_deviation_table(spark, sf_dir):
    """One-round deviations and clips against their bounds."""
    o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
    base = RunConfig(d=64, n_workers=16, m_prime=4, rounds=60, delta=0.05, alpha=2.6, alpha_s=2.6, loss="logistic")
    t = trajectories(o, {m: method(m, base) for m in ("onebit", "shared_sign", "no_flatten")})
    return measures.round_deviation(t, 2.6, 2.6, 1.0, 64, 16, 255)


@query
def sigmoid_embed_stationarity(spark, sf_dir):
    """Mean squared gradient of the smooth, not convex loss at step 1/sqrt(T), against its bound."""
    o = GradientOracle(planted_rows(spark, sf_dir), "sigmoid")
    rounds, alpha = 100, C.min_alpha(64)
    cfg = RunConfig(d=64, n_workers=16, m_prime=4, rounds=rounds, schedule="inv_sqrt", alpha=alpha, alpha_s=alpha, bound=0.5, loss="sigmoid")
    t = measures.with_objective(trajectories(o, {m: method(m, cfg) for m in ("plain", "onebit")}, every=5), o)
    rho, lam_s = C.rho_terms(alpha, alpha, 0.5, 64, 16), cfg.amplitudes()[1]
    bound = C.bound_nonconvex(0.25, rho["rho_printed"], rho["rho_server"], 0.5, 0.318, lam_s, 64, [cfg.step(0)] * rounds)
    return t.where(f"t < {rounds}").groupBy("run", "seed").agg(F.avg("grad_sq").alias("mean_grad_sq"), F.min("f").alias("least_f"), F.lit(bound).alias("bound"), F.lit(rho["rho_tight"]).alias("rho_tight"))


@query
def smoothness_table(spark, sf_dir):
    o = GradientOracle(planted_rows(spark, sf_dir), "sigmoid")
    pts = np.stack([s * planted() * (1 - 2 * (i % 2)) for i, s in enumerate((0.0, 0.5, 1.0, 2.0, 4.0))])
    return spark.createDataFrame(measures.smoothness_violations(o, pts, 0.318), "f double, allowed double, violated boolean")


@query
def oracle_probes(spark, sf_dir):
    """Variance and gradient bound of the oracles; the variance of the mini-batch falls as 1/m'."""
    rows = planted_rows(spark, sf_dir)
    out = [("logistic", mp, *estimate_sigma2(GradientOracle(rows, "logistic"), np.zeros(64), mp)) for mp in (1, 4, 16)]
    out += [("shard", 0, *estimate_sigma2(ShardOracle(rows, "logistic"), np.zeros(64), 1, 16)), ("coordinate", 0, *estimate_sigma2(CoordOracle(rows, "logistic"), np.zeros(64), 1, 64))]
    return spark.createDataFrame(out, "oracle string, m_prime int, sigma_sq double, top_norm double")


@query
def distributed_rounds(spark, sf_dir):
    """Three rounds of the distributed runner against the seed-parallel one: largest difference of iterates, by round."""
    o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
    cfg = method("onebit", RunConfig(d=64, n_workers=8, m_prime=4, rounds=3, delta=0.5, alpha=2.6, alpha_s=2.6, loss="logistic"))
    a = descend(o, cfg).trace
    b = {r["t"]: np.array(r["x"]) for r in trajectories(o, {"onebit": cfg}).where("t < 3").collect()}
    return spark.createDataFrame([(r["t"], float(np.abs(r["x"] - b[r["t"]]).max()), float(np.abs(r["x"]).max())) for r in a], "t int, difference double, top double")


@query
def oracle_descents(spark, sf_dir):
    """Distributed rounds with the shard and the coordinate oracle: loss of each iterate, and the bits that arrived."""
    rows = planted_rows(spark, sf_dir)
    out = []
    for name, oracle, up in (("shard", ShardOracle, "plain"), ("shard", ShardOracle, "onebit"), ("coordinate", CoordOracle, "onebit"), ("coordinate", CoordOracle, "vote")):
        o = oracle(rows, "logistic")
        base = RunConfig(d=64, n_workers=8, rounds=4, delta={"plain": 0.5, "onebit": 0.02, "vote": 0.05}[up], alpha=2.6, alpha_s=2.6, loss="logistic", server_amp="observed", bound=1.0 if name == "shard" else 8.0)
        r = descend(o, method(up, base))
        f, _ = o.evaluate(np.stack([t["x"] for t in r.trace] + [r.x_last]))
        out += [(name, up, t["t"], float(v), int(t["bits_up"]), int(t["bits_down"]), float(t["v"].sum())) for t, v in zip(r.trace, f, strict=False)] + [(name, up, 4, float(f[-1]), 0, 0, 0.0)]
    return spark.createDataFrame(out, "oracle string, method string, t int, f double, bits_up bigint, bits_down bigint, half_space double")


@query
def text_logistic(spark, sf_dir):
    """Quality labels from hashed words in unit rows of 1,024: sparse gradients, plain against one-bit."""
    words = hashed_words(load(spark, sf_dir, "documents", "doc_id", "text"), F.col("text"), "doc_id")
    labels = load(spark, sf_dir, "labels", "doc_id", "quality")
    rows = words.join(labels, "doc_id").select("doc_id", "coord", F.col("n").cast("double").alias("value"), (2.0 * F.col("quality") - 1).alias("y"))
    rows = rows.groupBy("doc_id", "y").agg(F.collect_list("coord").alias("coords"), F.collect_list("value").alias("counts"))  # at most 1,024 a row
    norm = F.sqrt(F.aggregate("counts", F.lit(0.0), lambda s, v: s + v * v))
    rows = rows.select("doc_id", "y", "coords", F.transform("counts", lambda v: v / norm).alias("values"))
    dense, at = numbered(rows, "doc_id")
    o = SparseOracle(dense, "logistic", at)
    base = RunConfig(d=1024, n_workers=8, m_prime=4, rounds=40, delta=2.0, loss="logistic", server_amp="observed")
    t = trajectories(o, {m: method(m, base) for m in ("plain", "onebit")}, every=20)
    return measures.with_objective(t, o, False).select("run", "seed", "t", "f", "bits_up", "bits_down")


# Stream.
@query
def stream_events_rounds(spark, sf_dir):
    """Eight micro-batches as eight rounds, against the same rounds on the stored batches."""
    from ditherspark.streaming.rounds import batch_round, rounds_from_stream

    base = shared_folder(spark)
    folder = f"{base}/stream-{uuid.uuid4().hex}"
    rows = event_rows(spark, sf_dir)
    last = rows.agg(F.max("row_id")).first()[0] or 0
    for i in range(8):
        rows.where(F.floor(F.col("row_id") * 8 / (last + 1)) == i).coalesce(1).write.mode("append").parquet(f"{folder}/in")
    source = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(f"{folder}/in")
    cfg = method("up_only", RunConfig(d=EVENT_D, n_workers=16, rounds=8, delta=0.2, bound=12.0))
    got = rounds_from_stream(source, cfg, f"{folder}/state")
    out, x = [], np.zeros(EVENT_D)
    for i, r in enumerate(got.trace):
        x = batch_round(rows.where(F.floor(F.col("row_id") * 8 / (last + 1)) == i), x, cfg, i)
        out.append((i, float(np.abs(r["x"] - x).max()), [float(v) for v in r["x"]]))
    return spark.createDataFrame(out, "t int, difference double, x array<double>")
