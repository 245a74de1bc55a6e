"""Dithered one-bit quantization and the packing of its levels.

One dither: sgn(x + tau), tau uniform on [-lam, lam], sgn(0) = +1. K dithers: the sum of K such signs, an odd or even
level between -K and K; its mean is K/lam times x limited to [-lam, lam].
"""

from __future__ import annotations

import numpy as np

from ditherspark.functions.rng import counter_hash


def checked(x: np.ndarray) -> np.ndarray:
    """``x`` as doubles; NaN and infinity are refused, since NaN would quietly count as +1."""
    x = np.asarray(x, np.float64)
    if not np.isfinite(x).all():
        raise ValueError("vectors must be finite")
    return x


def dither_levels(x: np.ndarray, lam: float, k: int, rng: np.random.Generator, mode: str = "binomial") -> np.ndarray:
    """Integer levels of every entry. ``hash`` draws K dithers each; ``binomial`` draws their number of successes at once,
    which has the same law and costs the same for any K."""
    if k < 1 or lam <= 0:
        raise ValueError("needs K >= 1 and a positive amplitude")
    x = checked(x)
    if mode == "hash" or k == 1:
        out = np.zeros(x.shape, np.int64)
        for _ in range(k):
            out += np.where(x + rng.uniform(-lam, lam, x.shape) >= 0, 1, -1)
        return out
    p = np.clip((1 + x / lam) / 2, 0, 1)
    return 2 * rng.binomial(k, p) - k


#: Hashes that one vectorised step of ``hashed_levels`` makes.
HASHES = 1 << 22


def hashed_levels(x: np.ndarray, lam: float, k: int, *key) -> np.ndarray:
    """Levels of ``x`` (rows, d) with K dithers each from ``counter_hash`` of the key, the column and the dither; key parts
    broadcast against rows, as (rows, 1)."""
    if k < 1 or lam <= 0:
        raise ValueError("needs K >= 1 and a positive amplitude")
    x, out = checked(x), np.zeros(x.shape, np.int64)
    coord = np.arange(x.shape[1])
    if k == 1:
        return np.where(x + lam * ((2.0 * counter_hash(*key, coord, 0) + 1) / 4294967296.0 - 1) >= 0, 1, -1)
    step = max(1, HASHES // max(1, x.size))
    for j in range(0, k, step):
        tau = lam * ((2.0 * counter_hash(*[np.asarray(p)[..., None] for p in key], coord[:, None], np.arange(j, min(k, j + step))) + 1) / 4294967296.0 - 1)
        out += 2 * (x[..., None] + tau >= 0).sum(axis=-1) - tau.shape[-1]
    return out


def dither_quantize(x: np.ndarray, lam: float, k: int, rng: np.random.Generator, mode: str = "binomial") -> np.ndarray:
    return dither_levels(x, lam, k, rng, mode) * (lam / k)


def level_bits(k: int) -> int:
    """Whole bits that a level of K dithers takes."""
    return max(1, int(k).bit_length())


def pack_numbers(numbers: np.ndarray, width: int) -> np.ndarray:
    """Rows of whole numbers below 2^width as rows of bytes, ``width`` bits apiece, first bit first."""
    numbers = np.asarray(numbers, np.int64)
    bits = (numbers[:, :, None] >> np.arange(width)) & 1
    return np.packbits(bits.reshape(len(numbers), numbers.shape[1] * width).astype(np.uint8), axis=1, bitorder="little")


def unpack_numbers(raw: np.ndarray, width: int, d: int) -> np.ndarray:
    bits = np.unpackbits(raw, axis=1, bitorder="little")[:, : d * width].reshape(len(raw), d, width).astype(np.int64)
    return (bits << np.arange(width)).sum(axis=2)


def pack_levels(q: np.ndarray, k: int) -> list[bytes]:
    """Each row's levels, (q+K)/2 in 0..K, in ``level_bits(k)`` bits apiece."""
    return [r.tobytes() for r in pack_numbers((np.asarray(q, np.int64) + k) >> 1, level_bits(k))]


def unpack_levels(packed: list[bytes], k: int, d: int) -> np.ndarray:
    raw = np.frombuffer(b"".join(packed), np.uint8).reshape(len(packed), -1)
    return 2 * unpack_numbers(raw, level_bits(k), d) - k
