"""Runs against bounds, exact values and replays, on small tables."""

import numpy as np
import pytest

from ditherspark.operators import measures
from ditherspark.operators.descent import descend, telescoping, trajectories
from ditherspark.operators.gradients import GradientOracle, OneSparseOracle
from ditherspark.operators.protocol import RunConfig, method
from ditherspark.plans import experiments as X
from ditherspark.plans.portable import EVENT_D, event_rows


@pytest.fixture(scope="module")
def events(spark, sf):
    """At sf0.01, where every coordinate has rows."""
    o = OneSparseOracle(event_rows(spark, sf.replace("0.001", "0.01")).cache())
    n, mu, rest = o.statistics(EVENT_D)
    return o, n / n.sum(), mu, rest


def test_exact_values_of_the_sparse_problem(events):
    o, p, mu, rest = events
    assert o.value(mu) == pytest.approx(rest)
    assert np.abs(o.full_grad(mu)).max() < 1e-9
    assert o.value(np.zeros(EVENT_D)) == pytest.approx(rest + float(p @ mu**2))


def test_telescoping_holds_for_every_method(events):
    o, _, mu, _ = events
    base = RunConfig(d=EVENT_D, n_workers=16, rounds=25, delta=0.05, bound=12.0)
    t = trajectories(o, {m: method(m, base) for m in ("plain", "onebit", "vote", "sign_mean", "random_k", "ternary", "shared_sign")}, x_star=mu)
    assert all(r.slack >= -1e-9 for r in telescoping(t, mu).collect())


def test_sign_methods_keep_above_the_floor_and_one_bit_goes_below(events):
    o, p, mu, _ = events
    floor = mu.sum() ** 2 / (1 / p).sum()
    assert floor > 0
    base = RunConfig(d=EVENT_D, n_workers=256, rounds=120, delta=0.1, bound=12.0)
    t = trajectories(o, {m: method(m, base) for m in ("observed", "vote", "sign_mean", "plain")}, every=119).where("t = 120").collect()
    gap = {r.run: float(p @ (np.array(r.x) - mu) ** 2) for r in t}
    assert gap["vote"] >= floor and gap["sign_mean"] >= floor
    assert gap["plain"] < gap["observed"] < floor


def test_runners_agree(spark, sf):
    for r in X.distributed_rounds(spark, sf).collect():
        assert r.difference < 1e-9


def test_resume_continues_the_same_run(spark, sf, tmp_path):
    o = GradientOracle(X.planted_rows(spark, sf).cache(), "logistic")
    cfg = method("onebit", RunConfig(d=64, n_workers=4, m_prime=2, rounds=3, delta=0.5, alpha=2.6, alpha_s=2.6, loss="logistic"))
    whole = descend(o, cfg)
    path = f"file://{tmp_path}/state"
    from dataclasses import replace

    descend(o, replace(cfg, rounds=2), state_path=path)
    rest = descend(o, cfg, state_path=path)
    assert np.allclose(whole.x_last, rest.x_last) and np.allclose(whole.x_avg, rest.x_avg) and len(rest.trace) == 1


def test_roundtrip_error_is_exact_and_bounded(spark, sf):
    r = measures.roundtrip_mse(spark.read.parquet(f"{sf}/embeddings.parquet"), 3.0, 1, seeds=8).first()
    assert abs(r.mse - r.exact) < 5 * r.std_error and r.mse <= r.bound and r.over_cap == 0 and r.clip_share <= r.clip_bound


def test_mean_of_workers_falls_as_one_over_n(spark, sf):
    r = measures.mean_roundtrip(spark.read.parquet(f"{sf}/embeddings.parquet"), 16, seeds=6).first()
    assert abs(r.cross_terms) < 5 * r.cross_std_error and r.deviation <= r.bound


def test_round_deviations_and_stationarity_keep_their_bounds(spark, sf):
    for r in X.round_deviation_table(spark, sf).collect():
        assert r.worker_deviation <= r.worker_bound and r.server_deviation <= r.server_bound
    for r in X.sigmoid_embed_stationarity(spark, sf).collect():
        assert r.mean_grad_sq <= r.bound
    assert not any(r.violated for r in X.smoothness_table(spark, sf).collect())
    for r in X.logistic_bound(spark, sf).collect():
        assert r.gap_at_most <= r.bound


def test_minibatch_variance_falls(spark, sf):
    v = {r.m_prime: r.sigma_sq for r in X.oracle_probes(spark, sf).where("oracle = 'logistic'").collect()}
    assert 3 < v[1] / v[4] < 5.5 and 3 < v[4] / v[16] < 5.5


def test_stream_replays_batches(spark, sf):
    rows = X.stream_events_rounds(spark, sf).collect()
    assert len(rows) == 8 and all(r.difference < 1e-9 for r in rows)


def test_average_iterate(spark, sf):
    assert all(abs(r.recomputed - r.kept) < 1e-9 for r in X.trace_average_iterate(spark, sf).collect())


def test_general_bound_and_split_of_deviations(spark, sf, events):
    for r in X.general_bound_table(spark, sf.replace("0.001", "0.01")).collect():
        assert r.gap <= r.bound
    o, _, mu, _ = events
    base = RunConfig(d=EVENT_D, n_workers=16, rounds=20, delta=0.05, bound=12.0)
    t = trajectories(o, {m: method(m, base) for m in ("onebit", "observed", "no_dither")}, x_star=mu).where("t < 20").collect()
    assert all(r.dev_total <= 2 * r.dev_server + 2 * r.dev_worker + 1e-9 for r in t)


def test_single_node_reaches_the_means(spark, sf):
    rows = X.single_node(spark, sf.replace("0.001", "0.01")).where("t = 120").collect()
    assert len(rows) == 3 and all(r.gap < 0.2 for r in rows)
