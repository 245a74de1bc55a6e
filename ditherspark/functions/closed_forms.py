"""Closed forms: amplitudes, traffic, moments of the quantizer, and the bounds that runs are held against.

d is the padded dimension, N the number of workers, K the number of dithers, B the bound on gradients; logarithms are
natural unless they count bits.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


# Column expressions.
def sgn1(x: Column) -> Column:
    """Sign with sgn(0) = +1 (Spark's ``signum`` gives 0 there)."""
    return F.when(x >= 0, 1).otherwise(-1)


def clamp(x: Column, lam) -> Column:
    """The quantizer's mean: x limited to [-lam, lam]."""
    lam = lam if isinstance(lam, Column) else F.lit(lam)
    return F.greatest(-lam, F.least(lam, x))


def soft_threshold(x: Column, lam) -> Column:
    """What the mean leaves behind: x minus its clamped value."""
    return x - clamp(x, lam)


# Amplitudes and traffic.
def next_pow2(d: int) -> int:
    if d < 1:
        raise ValueError("a dimension is at least 1")
    return max(2, 1 << (d - 1).bit_length())


def amplitudes(alpha: float, alpha_s: float, bound: float, d: int) -> tuple[float, float]:
    """(worker, server) dither amplitudes."""
    if d < 2:
        raise ValueError("the amplitude rule needs d >= 2")
    lam = alpha * bound * math.sqrt(math.log(d) / d)
    return lam, alpha_s * lam * math.sqrt(math.log(d))


def min_alpha(d: int) -> float:
    """An alpha from which the bounds' hypothesis u <= exp(u/8), u = alpha^2 ln d, surely holds."""
    return max(2.0, math.sqrt(26.10 / math.log(d)))


def wire_bits(d: int, n: int, k_down: int, eps_wire: str = "bits", packed: bool = False) -> dict[str, float]:
    """Bits of a round: each worker's message and signs, and the server's. ``packed`` counts whole bits a level."""
    eps = {"bits": d, "seed": 64, "none": 0}[eps_wire]
    level = math.ceil(math.log2(k_down + 1)) if packed else math.log2(k_down + 1)
    return {"up_worker": d + eps, "up_all": n * (d + eps), "down": level * d + eps}


def butterfly_ops(d: int) -> int:
    """Additions of one transform."""
    return d * int(math.log2(d))


# Probabilities.
def flatness_limit(alpha: float, d: int) -> float:
    """Largest entry after flattening, as a multiple of the norm, and see ``flatness_failure``."""
    return alpha * math.sqrt(math.log(d) / d)


def flatness_failure(alpha: float, d: int) -> float:
    return 2 * math.exp(-(alpha**2) * math.log(d) / 4)


def tail_bound(t: float, gamma: float, d: int) -> float:
    """P(largest entry > t * norm) for an orthonormal basis with entries up to gamma."""
    return 2 * d * math.exp(-(t**2) / (2 * gamma**2))


# Moments.
def quantizer_mse(lam: float, d: int, norm_sq: float, k: int) -> float:
    """Exact if no entry exceeds lam."""
    return (lam**2 * d - norm_sq) / k


def inner_second_moment(x: Sequence[float], y: Sequence[float], lam: float) -> float:
    """E <x, Q(y)>^2 for one dither."""
    dot = sum(a * b for a, b in zip(x, y, strict=True))
    return dot**2 + lam**2 * sum(a * a for a in x) - sum((a * b) ** 2 for a, b in zip(x, y, strict=True))


def matrix_quant_error(rows: Sequence[Sequence[float]], x: Sequence[float], lam: float) -> float:
    """E ||A Q(x) - A x||^2 for one dither."""
    return sum(lam**2 * a * a - (a * b) ** 2 for row in rows for a, b in zip(row, x, strict=True))


def variance_of_mean(variances: Sequence[float]) -> float:
    return sum(variances) / len(variances) ** 2


def roundtrip_mse_bound(alpha: float, bound: float, d: int, k: int) -> float:
    u = alpha**2 * math.log(d)
    return u * bound**2 / k + 8 * bound**2 * math.exp(-u / 8)


def mean_roundtrip_mse_bound(alpha: float, bound: float, d: int, n: int, each: float | None = None) -> float:
    """Deviation of the workers' averaged roundtrip; ``each`` is a worker's mean squared error, its bound by default."""
    each = roundtrip_mse_bound(alpha, bound, d, 1) if each is None else each
    return each / n + 8 * n * bound**2 * math.exp(-(alpha**2) * math.log(d) / 8)


def round_deviation_bounds(alpha: float, alpha_s: float, bound: float, d: int, n: int, k: int) -> tuple[float, float]:
    """(server mean against true mean, sent direction against server mean), mean squares of one round."""
    u, us, b2 = alpha**2 * math.log(d), alpha_s**2 * math.log(d), bound**2
    first = 2 * u * b2 / n + 8 * n * b2 * math.exp(-u / 8)
    second = us * alpha**2 * b2 * math.log(d) / k + 8 * u * b2 * math.exp(-us / 8)
    return first, second


# Convergence.
def bound_plain(dist_sq: float, deltas: Sequence[float], grad_sq: Sequence[float], sigma_sq: float, n: int) -> dict[str, float]:
    """Terms of the gap's bound for uncompressed descent."""
    c, sq = 1 / sum(deltas), sum(x * x for x in deltas)
    return {"start": c * dist_sq / 2, "gradient": c * sum(a * a * g for a, g in zip(deltas, grad_sq, strict=True)), "variance": 2 * sigma_sq / n * sq * c}


def bound_general(plain: dict[str, float], deltas: Sequence[float], dev_sq: Sequence[float], cross: Sequence[float]) -> dict[str, float]:
    """Adds what a compressed direction costs, from its measured deviation and inner products."""
    c = 1 / sum(deltas)
    more = {"deviation": 2 * c * sum(a * a * v for a, v in zip(deltas, dev_sq, strict=True)), "drift": c * sum(a * v for a, v in zip(deltas, cross, strict=True))}
    return plain | more


def bound_compressed(plain: dict[str, float], alpha: float, alpha_s: float, bound: float, d: int, n: int, k: int, delta: float, eta: float) -> dict[str, float]:
    """Adds the two-way scheme's terms at a constant step."""
    ln = math.log(d)
    u, us, b2 = alpha**2 * ln, alpha_s**2 * ln, bound**2
    return plain | {
        "worker_share": alpha**2 * b2 * delta * 8 * ln / n,
        "server_share": alpha**2 * b2 * delta * 4 * alpha_s**2 * ln**2 / k,
        "clip_sq": 32 * b2 * delta * (n * math.exp(-u / 8) + u * math.exp(-us / 8)),
        "clip_distance": 4 * bound * eta * (n * math.exp(-u / 8) + alpha * math.sqrt(ln) * math.exp(-us / 8)),
    }


def rho_terms(alpha: float, alpha_s: float, bound: float, d: int, n: int) -> dict[str, float]:
    """Distortion of directions by clipping: the worker's as printed (with N) and without N, and the server's."""
    lam, lam_s = amplitudes(alpha, alpha_s, bound, d)
    per = 2 * (bound + lam * math.sqrt(d)) * math.exp(-(alpha**2) * math.log(d) / 4)
    return {"rho_printed": n * per, "rho_tight": per, "rho_server": 2 * math.sqrt(d) * (lam + lam_s) * math.exp(-(alpha_s**2) * math.log(d) / 4)}


def bound_nonconvex(f0_gap: float, rho: float, rho_s: float, bound: float, smooth: float, lam_s: float, d: int, deltas: Sequence[float]) -> float:
    """Bound on the weighted mean squared gradient norm."""
    c = 1 / sum(deltas)
    return c * f0_gap + (rho + rho_s) * bound + smooth * lam_s**2 * d / 2 * c * sum(x * x for x in deltas)
