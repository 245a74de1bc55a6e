"""Hand examples, identities, enumeration and bounds of the kernels."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from ditherspark.functions import closed_forms as C
from ditherspark.functions import rng
from ditherspark.operators.basis import BASES, dense_basis, is_flat_basis, sign_butterfly
from ditherspark.operators.codec import decode, decode_rows, encode, encode_rows, padded, roundtrip
from ditherspark.operators.protocol import RunConfig, method, send_down, send_up, traffic
from ditherspark.operators.quantize import dither_levels, dither_quantize, level_bits, pack_levels, unpack_levels


def test_butterfly_by_hand():
    assert sign_butterfly(np.array([[3.0, 1.0]])).tolist() == [[4, 2]]
    assert sign_butterfly(np.array([[1.0, 2.0, 3.0, 4.0]])).tolist() == [[10, -2, -4, 0]]
    x = np.random.default_rng(0).normal(size=(3, 32))
    assert np.allclose(sign_butterfly(sign_butterfly(x)), 32 * x)
    with pytest.raises(ValueError):
        sign_butterfly(np.zeros((1, 3)))


@pytest.mark.parametrize("name", BASES)
def test_bases_are_isometries_with_small_entries(name):
    b, d = BASES[name], 16
    eye = np.eye(d)
    m = b.forward(eye.copy())
    assert np.allclose(b.adjoint(m.copy()), eye) and np.allclose((m**2).sum(1), 1)
    assert np.abs(m).max() <= b.gamma(d) + 1e-12


def test_dense_basis_is_flat_and_equals_the_fast_form(spark):
    entries = dense_basis(spark, 3)
    assert is_flat_basis(entries.select("k", "l", (F.col("s") / math.sqrt(8)).alias("value")), 8)
    assert not is_flat_basis(entries.select("k", "l", F.when(F.col("k") == F.col("l"), 1.0).otherwise(0.0).alias("value")), 8)
    dense = np.zeros((8, 8))
    for r in entries.collect():
        dense[r.k, r.l] = r.s
    assert np.array_equal(dense, sign_butterfly(np.eye(8)).T)


def test_sign_of_zero_and_rejected_inputs(spark):
    assert spark.range(1).select(C.sgn1(F.lit(0.0)).alias("s")).first().s == 1
    assert spark.range(1).select(C.sgn1(F.lit(-0.0)).alias("s")).first().s == 1
    g = np.random.default_rng(0)
    for bad in (np.nan, np.inf):
        with pytest.raises(ValueError):
            dither_levels(np.array([bad]), 1.0, 1, g)
    for lam, k in ((0.0, 1), (1.0, 0)):
        with pytest.raises(ValueError):
            dither_levels(np.zeros(2), lam, k, g)
    with pytest.raises(ValueError):
        padded([[1.0], [1.0, 2.0]])
    with pytest.raises(ValueError):
        padded([None, [1.0]])
    with pytest.raises(ValueError):
        C.amplitudes(2, 2, 1, 1)


def test_integer_dither_is_exactly_unbiased():
    limit = 7
    for z in range(-limit, limit + 1):
        signs = [1 if z + tau >= 0 else -1 for tau in range(-limit, limit)]
        assert sum(signs) == 2 * z


def test_enumerated_roundtrip_of_four_entries():
    """Over all sign strings and an integer grid of dithers, decoding gives the input on average, with the exact error."""
    x, limit = np.array([3, -1, 0, 2]), 16
    total, err = np.zeros(4), 0.0
    for eps in itertools.product((-1, 1), repeat=4):
        z = sign_butterfly((x * eps)[None].astype(float))[0]
        assert np.abs(z).max() <= limit
        per = [np.array([1 if v + t >= 0 else -1 for t in range(-limit, limit)]) for v in z]
        mean = np.array([p.mean() for p in per])
        total += np.array(eps) * sign_butterfly(mean[None])[0] * limit / 4
        err += sum((limit**2 - v * v) for v in z) / 4  # independent entries: variances add under an isometry
    assert np.allclose(total / 16, x)
    assert np.isclose(err / 16, (limit**2 * 4 - (4 * x @ x)) / 4)


def test_levels_have_parity_range_and_packing():
    g = np.random.default_rng(1)
    for k in (1, 3, 7, 255):
        for mode in ("hash", "binomial"):
            q = dither_levels(g.normal(size=(5, 16)), 2.0, k, g, mode)
            assert (np.abs(q) <= k).all() and ((q - k) % 2 == 0).all()
            packed = pack_levels(q, k)
            assert all(len(p) == -(-16 * level_bits(k) // 8) for p in packed)
            assert np.array_equal(unpack_levels(packed, k, 16), q)
    assert set(np.unique(dither_levels(np.zeros(4000), 1.0, 3, g))) == {-3, -1, 1, 3}


def test_quantizer_mean_is_the_clamp_and_its_error_exact():
    g, lam = np.random.default_rng(2), 1.0
    x = np.linspace(-2, 2, 9)
    q = dither_quantize(np.repeat(x[None], 20000, 0), lam, 1, g)
    assert np.abs(q.mean(0) - np.clip(x, -lam, lam)).max() < 4 / math.sqrt(20000)
    y = np.linspace(-0.9, 0.9, 8)
    for k in (1, 4):
        err = ((dither_quantize(np.repeat(y[None], 20000, 0), lam, k, g) - y) ** 2).sum(1)
        assert abs(err.mean() - C.quantizer_mse(lam, 8, float(y @ y), k)) < 4 * err.std() / math.sqrt(20000)


def test_codec_through_messages(spark, sf):
    df = spark.read.parquet(f"{sf}/embeddings.parquet").limit(20)
    lam = 0.51
    m = encode(df, lam, 3)
    assert {(r.k, r.d, len(r.packed), len(r.eps)) for r in m.collect()} == {(3, 64, 16, 8)}
    got = {r.id: np.array(r.v) for r in decode(m).collect()}
    for r in df.collect():
        x = np.array([r.embedding], float)
        q, eps, _ = encode_rows(x, np.array([r.vec_id]), lam, 3, 0)
        assert np.allclose(decode_rows(q, eps, lam, 3)[0], got[r.vec_id])
        assert np.linalg.norm(got[r.vec_id]) <= lam * 8 + 1e-9
    back = roundtrip(df, lam, 3).agg(F.avg("err_sq")).first()[0]
    assert abs(back - C.quantizer_mse(lam, 64, 1.0, 3)) < 1.5


def test_odd_length_is_padded_and_cut_back(spark):
    df = spark.createDataFrame([(1, [1.0, -2.0, 0.5])], "vec_id long, embedding array<double>")
    row = decode(encode(df, 3.0, 255)).first()
    assert len(row.v) == 3


def test_amplitudes_and_bits():
    assert C.amplitudes(2, 2, 1, 64)[0] == pytest.approx(0.5098, abs=1e-4)
    assert C.min_alpha(64) == pytest.approx(2.505, abs=1e-2) and C.min_alpha(1024) == 2.0
    b = C.wire_bits(64, 16, 255)
    assert b == {"up_worker": 128, "up_all": 2048, "down": 576.0}
    assert C.wire_bits(64, 16, 1)["down"] == 128
    assert traffic(method("onebit", RunConfig(d=64, n_workers=16))) == (2048.0, 576.0)


def test_shared_signs_decode_like_the_sum():
    g = np.random.default_rng(3).normal(size=(6, 16)) * 0.1
    base = RunConfig(d=16, n_workers=6, eps_scope="round")
    lam, _ = base.amplitudes()
    q, eps, _ = encode_rows(g, np.arange(6), lam, 1, 0, 5, "worker", "butterfly", "round")
    each = decode_rows(q, eps, lam, 1).sum(0)
    got, _ = send_up(g, np.arange(6), base, 5, 0)
    assert np.allclose(got.sum(0), each)


def test_sign_methods_stay_in_the_half_space():
    rng_ = np.random.default_rng(4)
    for d in (2, 16):
        g = np.zeros((8, d))
        g[np.arange(8), rng_.integers(0, d, 8)] = rng_.normal(size=8)
        for name in ("vote", "sign_mean"):
            cfg = method(name, RunConfig(d=d, n_workers=8))
            up, _ = send_up(g, np.arange(8), cfg, 0, 0)
            v, _ = send_down(up.mean(0), cfg, 0, 0)
            assert v.sum() >= 0
    one_negative = np.array([[-1.0, 0.0]])
    cfg = method("vote", RunConfig(d=2, n_workers=1))
    assert send_down(send_up(one_negative, np.arange(1), cfg, 0, 0)[0].mean(0), cfg, 0, 0)[0].sum() == 0


def test_portable_hash_agrees_with_python(spark):
    got = spark.range(5).select(rng.hash60(0, "a", F.col("id")).alias("h")).collect()
    assert [r.h for r in got] == [rng.hash60_py(0, "a", i) for i in range(5)]


def test_bounds_fall_and_rise_as_they_should():
    p = C.bound_plain(1.0, [0.1] * 10, [1.0] * 10, 1.0, 4)
    a = C.bound_compressed(p, 3, 3, 1, 64, 16, 1, 0.1, 1.0)
    b = C.bound_compressed(p, 3, 3, 1, 64, 16, 255, 0.1, 1.0)
    assert b["server_share"] == pytest.approx(a["server_share"] / 255) and sum(b.values()) < sum(a.values())
    assert a["worker_share"] + a["server_share"] == pytest.approx(562.3, rel=1e-3)  # 5,623 at step 1
    r = C.rho_terms(3, 3, 1, 64, 16)
    assert r["rho_printed"] == pytest.approx(16 * r["rho_tight"])
    assert C.tail_bound(1, 0.1, 64) < C.tail_bound(0.5, 0.1, 64)
