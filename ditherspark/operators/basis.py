"""Orthonormal bases that spread a vector's energy: each has ``forward``, ``adjoint`` and its largest entry ``gamma``.

Kernels take a batch (n, d) and work along the last axis. The integer path is built of column expressions only.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sign_butterfly(x: np.ndarray) -> np.ndarray:
    """The +-1 transform of rows of length 2^k, unnormalised: d log d additions."""
    n, d = x.shape
    if d & (d - 1):
        raise ValueError("the length must be a power of two")
    out, half = x.copy(), 1
    while half < d:
        pairs = out.reshape(n, d // (2 * half), 2, half)
        top, bottom = pairs[:, :, 0].copy(), pairs[:, :, 1].copy()
        pairs[:, :, 0] = top + bottom
        pairs[:, :, 1] = top - bottom
        half *= 2
    return out


class FlatBasis:
    """An orthonormal map. ``complex_valued`` ones double the coordinates: real parts, then imaginary parts."""

    name = "identity"

    def forward(self, x: np.ndarray) -> np.ndarray:
        return x

    def adjoint(self, z: np.ndarray) -> np.ndarray:
        return z

    def gamma(self, d: int) -> float:
        return 1.0


class Identity(FlatBasis):
    """No spreading."""


class SignButterfly(FlatBasis):
    name = "butterfly"

    def forward(self, x):
        return sign_butterfly(x) / np.sqrt(x.shape[1])

    adjoint = forward  # symmetric and orthonormal

    def gamma(self, d):
        return 1 / np.sqrt(d)


class Fourier(FlatBasis):
    """The discrete Fourier basis on reals: real and imaginary parts are quantised apart, so a message has 2d entries."""

    name = "fourier"

    def forward(self, x):
        z = np.fft.fft(x, norm="ortho", axis=1)
        return np.concatenate([z.real, z.imag], axis=1)

    def adjoint(self, z):
        d = z.shape[1] // 2
        return np.fft.ifft(z[:, :d] + 1j * z[:, d:], norm="ortho", axis=1).real

    def gamma(self, d):
        return 1 / np.sqrt(d)


class Cosine(FlatBasis):
    """An orthonormal basis with entries up to sqrt(2/d), through a Fourier transform of twice the length."""

    name = "cosine"

    def forward(self, x):
        n, d = x.shape
        wide = np.fft.fft(np.concatenate([x, np.zeros_like(x)], axis=1), axis=1)[:, :d]
        k = np.arange(d)
        out = (wide * np.exp(-1j * np.pi * k / (2 * d))).real * np.sqrt(2 / d)
        out[:, 0] /= np.sqrt(2)
        return out

    def adjoint(self, z):
        n, d = z.shape
        k = np.arange(d)
        w = z * np.sqrt(2 / d)
        w[:, 0] = z[:, 0] / np.sqrt(d)
        wide = np.concatenate([w * np.exp(1j * np.pi * k / (2 * d)), np.zeros_like(z)], axis=1)
        return (np.fft.ifft(wide, axis=1) * 2 * d).real[:, :d]

    def gamma(self, d):
        return np.sqrt(2 / d)


BASES = {b.name: b for b in (SignButterfly(), Fourier(), Cosine(), Identity())}


def dense_basis(spark, k: int) -> DataFrame:
    """(k, l, s): the +-1 matrix of size 2^k by parity of common bits; a test oracle, d^2 rows."""
    d = 1 << k
    rows, cols = spark.range(d).withColumnRenamed("id", "k"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(d - 1).cast("long")))
    return rows.select("k", cols.alias("l")).withColumn("s", 1 - 2 * (F.bit_count(F.col("k").bitwiseAND(F.col("l"))) % 2))


def is_flat_basis(entries: DataFrame, d: int, tol: float = 1e-9) -> bool:
    """Whether (k, l, value) are an orthonormal matrix whose entries all have magnitude 1/sqrt(d)."""
    flat = entries.where(F.abs(F.abs("value") - 1 / d**0.5) > tol).isEmpty()
    a, b = entries.select("k", "l", F.col("value").alias("va")), entries.select(F.col("k").alias("k2"), "l", F.col("value").alias("vb"))
    gram = a.join(b, "l").groupBy("k", "k2").agg(F.sum(F.col("va") * F.col("vb")).alias("g"))
    same = F.when(F.col("k") == F.col("k2"), 1.0).otherwise(0.0)
    return flat and entries.count() == d * d and gram.where(F.abs(F.col("g") - same) > tol).isEmpty()


# Integer path: generated column expressions, no Python in the tasks.
def bound(value: Column, use) -> Column:
    """``use(value)`` with ``value`` computed once a row."""
    return F.transform(F.array(value), use)[0]


def _stage(d: int, half: int):
    """Sums and differences of entries that lie ``half`` apart."""
    at = F.sequence(F.lit(0), F.lit(d - 1))

    def pair(a: Column) -> Column:
        return F.transform(at, lambda i: F.when(i.bitwiseAND(F.lit(half)) == 0, F.get(a, i) + F.get(a, i + half)).otherwise(F.get(a, i - half) - F.get(a, i)))

    return pair


def butterfly_expr(values: Column, d: int) -> Column:
    """The unnormalised transform of an array of longs of length d = 2^k: k stages of sums and differences."""
    out, half = values, 1
    while half < d:
        out = bound(out, _stage(d, half))
        half *= 2
    return out
