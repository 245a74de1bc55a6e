"""Messages as bytes, their size, what crosses exchanges, and runs that stop and start again."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from ditherspark.functions import closed_forms as C
from ditherspark.functions.rng import counter_hash
from ditherspark.operators.descent import descend, server_sums, trajectories, worker_messages
from ditherspark.operators.gradients import CoordOracle, GradientOracle, OneSparseOracle, ShardOracle, SparseOracle
from ditherspark.operators.protocol import RunConfig, encode_up, method, pack_down, pack_up, send_down, send_up, traffic, unpack_down, unpack_up
from ditherspark.plans import experiments as X
from ditherspark.plans.portable import EVENT_D, event_rows

METHODS = ("plain", "onebit", "up_only", "down_only", "vote", "sign_mean", "no_flatten", "no_dither", "shared_sign", "observed", "fourier", "cosine", "random_k", "ternary")


@pytest.mark.parametrize("wire", ["bits", "seed"])
@pytest.mark.parametrize("name", METHODS)
def test_what_arrives_is_what_was_meant(name, wire):
    g = np.random.default_rng(3).normal(size=(9, 48)) / 7
    cfg = replace(method(name, RunConfig(d=48, n_workers=9, k=7)), eps_wire=wire)
    packed, eps = pack_up(encode_up(g, np.arange(9), cfg, 5, 1), cfg)
    meant, _ = send_up(g, np.arange(9), cfg, 5, 1)
    assert np.allclose(unpack_up(packed, eps, cfg).sum(0), meant.sum(0), atol=1e-12)
    w = meant.sum(0) / 9
    message, _ = pack_down(w, cfg, 5, 1)
    assert np.array_equal(unpack_down(message, cfg), send_down(w, cfg, 5, 1)[0])
    up, down = traffic(cfg)
    sizes = 8 * (packed.size + eps.size), 8 * len(message)
    if name == "random_k":  # whole bits for indices
        assert up <= sizes[0] <= up + 9 * 8 + 9 * cfg.keep
    elif name == "ternary":  # two bits for three levels
        assert sizes[0] == 9 * (2 * 48 + 32)
    else:
        assert sizes[0] == up
    assert sizes[1] == down


def test_seeds_take_eight_bytes_where_sign_strings_take_d_bits():
    base = RunConfig(d=1024, n_workers=4)
    bits, seed = (traffic(replace(base, eps_wire=w)) for w in ("bits", "seed"))
    assert bits[0] - seed[0] == 4 * (1024 - 64) and bits[1] - seed[1] == 1024 - 64


def test_counter_hash_is_even_and_without_pattern():
    h = counter_hash(0, 1, np.arange(400)[:, None], np.arange(256))
    assert abs((h & np.uint64(1)).astype(float).mean() - 0.5) < 0.01
    s = 1 - 2.0 * (h & np.uint64(1)).astype(float)
    off = s @ s.T / 256 - np.eye(400)
    assert np.abs(off).max() < 0.4 and abs(off.mean()) < 0.001
    assert counter_hash(1 << 40) != counter_hash((1 << 40) + (1 << 33))


def test_only_bytes_cross_the_exchange(spark, sf):
    o = GradientOracle(X.planted_rows(spark, sf), "logistic")
    cfg = method("onebit", RunConfig(d=64, n_workers=8, m_prime=2, alpha=2.6, alpha_s=2.6, loss="logistic"))
    m = worker_messages(o.worker_gradients(np.zeros(64), 0, cfg), cfg, 0, 0)
    assert m.columns == ["worker", "packed", "eps", "clipped"]
    assert {(len(r.packed), len(r.eps)) for r in m.collect()} == {(8, 8)}
    plan = server_sums(m, cfg)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning(worker" in plan
    run = descend(o, replace(cfg, rounds=1))
    assert (run.trace[0]["bits_up"], run.trace[0]["bits_down"]) == traffic(cfg)


def test_a_late_round_still_broadcasts_its_draws(spark, sf):
    o = OneSparseOracle(event_rows(spark, sf), m=1000)
    cfg = RunConfig(d=16, n_workers=64)
    plan = lambda t: o.worker_gradients(np.zeros(16), t, cfg)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan(10**6) and "SortMergeJoin" not in plan(10**6)
    late = {(r.t, r.worker, r.row_id) for r in o.drawn(1, 4, 2, 0, 7).collect()}
    assert late == {(r.t, r.worker, r.row_id) for r in o.drawn(8, 4, 2, 0).where("t = 7").collect()}


def test_all_partial_sums_are_merged_before_the_driver(spark, sf):
    rows = X.planted_rows(spark, sf).repartition(23).cache()
    o = GradientOracle(rows, "logistic")
    pts = np.random.default_rng(0).normal(size=(70, 64))
    f, g = o.evaluate(pts, True)
    a = np.array([r.x for r in rows.orderBy("row_id").collect()])
    y = np.array([r.y for r in rows.orderBy("row_id").collect()])
    z = a @ pts.T
    assert np.allclose(f, np.logaddexp(0, -y[:, None] * z).mean(0)) and np.allclose(g, (-y[:, None] / (1 + np.exp(y[:, None] * z))).T @ a / len(a))


def test_shards_and_coordinates_descend(spark, sf):
    rows = {(r.oracle, r.method, r.t): r for r in X.oracle_descents(spark, sf).collect()}
    assert rows["shard", "plain", 4].f < rows["shard", "plain", 0].f and rows["shard", "plain", 0].bits_up == 16 * rows["shard", "onebit", 0].bits_up
    assert all(r.half_space >= 0 for (o, m, _), r in rows.items() if m == "vote")


def test_coordinate_gradients_are_unbiased(spark, sf):
    o = CoordOracle(X.planted_rows(spark, sf).cache(), "logistic")
    x = np.full(64, 0.1)
    g = np.array([r.g for r in o.worker_gradients(x, 0, RunConfig(d=64, n_workers=6000)).collect()])
    assert ((g != 0).sum(1) <= 1).all()
    full = o.full_grad(x)
    assert np.linalg.norm(g.mean(0) - full) < 4 * 64**0.5 * np.linalg.norm(full) / 6000**0.5


def test_sparse_rows_give_the_dense_gradients(spark):
    rows = [(0, [1, 5], [0.5, -1.0], 1.0), (1, [0], [2.0], -1.0), (2, [], [], 1.0)]
    s = SparseOracle(spark.createDataFrame(rows, "row_id long, coords array<int>, values array<double>, y double"), "logistic")
    full = [(i, [dict(zip(c, v)).get(k, 0.0) for k in range(8)], y) for i, c, v, y in rows]
    d = GradientOracle(spark.createDataFrame(full, "row_id long, x array<double>, y double"), "logistic")
    x = np.linspace(-1, 1, 8)
    assert np.allclose(s.full_grad(x), d.full_grad(x)) and np.isclose(s.value(x), d.value(x))


def test_dense_numbers(spark):
    rows = spark.range(1000).select((F.col("id") * 37).alias("k"))
    got, n = X.numbered(rows, "k", 90)
    assert n == 1000 and sorted(r.row_id for r in got.collect()) == list(range(1000))


def test_a_stream_goes_on_where_it_stopped(spark, sf, tmp_path):
    from ditherspark.streaming.rounds import rounds_from_stream

    rows = event_rows(spark, sf)
    cfg = method("up_only", RunConfig(d=EVENT_D, n_workers=8, rounds=8, delta=0.2, bound=12.0))
    part = lambda i: rows.where(f"row_id % 4 = {i}").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    read = lambda: spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    part(0), part(1)
    first = rounds_from_stream(read(), cfg, f"file://{tmp_path}/a")
    part(2), part(3)
    rest = rounds_from_stream(read(), cfg, f"file://{tmp_path}/a")
    assert len(first.trace) == 2 and len(rest.trace) == 4
    assert np.array_equal(rest.trace[1]["x"], first.x_last)
    whole = rounds_from_stream(read(), cfg, f"file://{tmp_path}/b")
    assert np.allclose(whole.x_last, rest.x_last)


def test_variance_of_a_mean(spark, sf):
    assert C.variance_of_mean([3.0] * 12) == pytest.approx(0.25)
    o = ShardOracle(X.planted_rows(spark, sf).cache(), "logistic")
    cfg = RunConfig(d=64, n_workers=64, m_prime=1)
    g = np.array([r.g for r in GradientOracle(o.rows, "logistic").worker_gradients(np.zeros(64), 0, cfg).collect()])
    each = ((g - g.mean(0)) ** 2).sum(1).mean()
    means = g.reshape(8, 8, 64).mean(1)
    assert 0.5 < ((means - g.mean(0)) ** 2).sum(1).mean() / C.variance_of_mean([each] * 8) < 1.6


def test_large_runs_are_refused_by_the_one_task_runner(spark, sf):
    o = OneSparseOracle(event_rows(spark, sf), m=1000)
    with pytest.raises(ValueError, match="descend"):
        trajectories(o, {"a": RunConfig(d=16, n_workers=1 << 20, rounds=100)})


def test_mean_bound_has_its_clipping_term():
    assert C.mean_roundtrip_mse_bound(2, 1, 64, 4) > (C.roundtrip_mse_bound(2, 1, 64, 1) + 0) / 4
    assert C.mean_roundtrip_mse_bound(2, 1, 64, 1) > C.roundtrip_mse_bound(2, 1, 64, 1)
