"""The vector codec: random signs, flat basis, dithered levels, packed bits, and back.

A message row is (id, q packed, eps packed, lam, k, d): all a decoder needs. Encoding and decoding are narrow maps over
Arrow batches, with no shuffle; ``roundtrip`` fuses them and skips the packing. Vectors are padded with zeros to a power
of two and cut back after decoding. Null vectors, NaN, infinity and ragged lengths are refused.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from ditherspark.functions.closed_forms import next_pow2
from ditherspark.functions.rng import STREAMS, counter_hash, stream
from ditherspark.operators.basis import BASES
from ditherspark.operators.quantize import checked, dither_levels, hashed_levels, level_bits, pack_levels, unpack_numbers

MESSAGE = "id bigint, packed binary, eps binary, lam double, k int, d int, width int"


def sign_keys(seed: int, party: str, t: int, ids: np.ndarray, scope: str = "worker") -> np.ndarray:
    """Two 32-bit numbers for each id, from which its sign string follows; with scope ``round`` the same for all."""
    ids = np.zeros(len(ids), np.int64) if scope == "round" else np.asarray(ids, np.int64)
    return counter_hash(seed, STREAMS[f"eps-{party}"], t, ids[:, None], np.arange(2)).astype(np.uint32)


def signs_of(keys: np.ndarray, d: int) -> np.ndarray:
    """A row of -1/+1 for each key."""
    return 1 - 2 * (counter_hash(keys[:, :1], keys[:, 1:], np.arange(d)) & np.uint64(1)).astype(np.int64)


def signs(seed: int, party: str, t: int, ids: np.ndarray, d: int, scope: str = "worker") -> np.ndarray:
    return signs_of(sign_keys(seed, party, t, ids, scope), d)


def encode_rows(x: np.ndarray, ids: np.ndarray, lam: float, k: int, seed: int, t: int = 0, party: str = "worker", basis: str = "butterfly", scope: str = "worker", dither: bool = True, mode: str = "hash") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(levels, signs, flattened) of padded rows ``x``. ``hash`` draws K dithers an entry, ``binomial`` their number at
    once, whose cost doesn't depend on K."""
    eps = signs(seed, party, t, ids, x.shape[1], scope) if basis != "identity" else np.ones(x.shape, np.int64)
    z = BASES[basis].forward(checked(x) * eps)
    if not dither:
        return np.where(z >= 0, k, -k), eps, z
    if mode == "hash" or k == 1:
        return hashed_levels(z, lam, k, seed, STREAMS[f"tau-{party}"], t, np.asarray(ids, np.int64)[:, None]), eps, z
    q = [dither_levels(z[i], lam, k, stream(seed, f"tau-{party}", t, int(n))) for i, n in enumerate(ids)]
    return np.stack(q) if q else np.zeros(z.shape, np.int64), eps, z


def decode_rows(q: np.ndarray, eps: np.ndarray, lam: float, k: int, basis: str = "butterfly") -> np.ndarray:
    return BASES[basis].adjoint(q * (lam / k)) * eps


def vectors(column: pa.Array, d: int | None = None) -> tuple[np.ndarray, int]:
    """(rows padded with zeros to ``d`` or the next power of two, their length) of a list column, without Python lists."""
    if column.null_count:
        raise ValueError("vectors must not be null")
    n = len(column)
    sizes = pc.list_value_length(column).to_numpy(zero_copy_only=False)
    if n and (sizes != sizes[0]).any():
        raise ValueError("vectors differ in length")
    size = int(sizes[0]) if n else 1
    flat = column.flatten()
    if flat.null_count:
        raise ValueError("entries must not be null")
    out = np.zeros((n, d or next_pow2(size)))
    out[:, :size] = flat.to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, size) if n else 0
    return out, size


def padded(vectors: list, d: int | None = None) -> np.ndarray:
    if any(v is None for v in vectors):
        raise ValueError("vectors must not be null")
    sizes = {len(v) for v in vectors}
    if len(sizes) > 1:
        raise ValueError("vectors differ in length")
    size = sizes.pop() if sizes else 1
    out = np.zeros((len(vectors), d or next_pow2(size)))
    out[:, :size] = np.array(vectors, np.float64).reshape(len(vectors), size)
    return out


def listed(rows: np.ndarray) -> pa.Array:
    """Rows of doubles as a list column."""
    return pa.ListArray.from_arrays(np.arange(0, rows.size + 1, max(1, rows.shape[1]), dtype=np.int32), pa.array(np.ascontiguousarray(rows, np.float64).ravel()))


def bytes_of(column: pa.Array) -> np.ndarray:
    """Equally long byte strings as rows of bytes."""
    n = len(column)
    raw = np.frombuffer(b"".join(column.to_pylist()), np.uint8)
    return raw.reshape(n, -1) if n else np.zeros((0, 0), np.uint8)


def packed_column(rows: np.ndarray) -> pa.Array:
    """Rows of bytes as a binary column."""
    ends = np.arange(len(rows) + 1, dtype=np.int32) * np.int32(rows.shape[1])
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(rows, np.uint8))])


def encode_many(df: DataFrame, lam: float, ks: tuple[int, ...], seed: int = 0, basis: str = "butterfly", id_col: str = "vec_id", col: str = "embedding", mode: str = "hash") -> DataFrame:
    """One message a row and K, in one scan."""

    def run(batches):
        for b in batches:
            x, width = vectors(b["v"])
            ids, n = b["id"].to_numpy(zero_copy_only=False), b.num_rows
            same = lambda v, t: pa.array(np.full(n, v), t)
            for k in ks:
                q, eps, _ = encode_rows(x, ids, lam, k, seed, basis=basis, mode=mode)
                cols = [b["id"], pa.array(pack_levels(q, k), pa.binary()), packed_column(np.packbits(eps > 0, axis=1, bitorder="little")), same(lam, pa.float64()), same(k, pa.int32()), same(x.shape[1], pa.int32()), same(width, pa.int32())]
                yield pa.RecordBatch.from_arrays(cols, ["id", "packed", "eps", "lam", "k", "d", "width"])

    return df.selectExpr(f"cast({id_col} as bigint) id", f"cast({col} as array<double>) v").mapInArrow(run, MESSAGE)


def encode(df: DataFrame, lam: float, k: int = 1, seed: int = 0, basis: str = "butterfly", id_col: str = "vec_id", col: str = "embedding", mode: str = "hash") -> DataFrame:
    """One message a row."""
    return encode_many(df, lam, (k,), seed, basis, id_col, col, mode)


def decode(messages: DataFrame, basis: str = "butterfly") -> DataFrame:
    """(id, v): vectors of the original length. Messages of one shape (K, d, length) are decoded together."""

    def run(batches):
        for b in batches:
            shape = np.stack([b[c].to_numpy(zero_copy_only=False) for c in ("k", "d", "width")], axis=1)
            for k, d, width in np.unique(shape, axis=0).tolist():
                part = b.filter(pa.array((shape == (k, d, width)).all(axis=1)))
                q = 2 * unpack_numbers(bytes_of(part["packed"]), level_bits(k), 2 * d if basis == "fourier" else d) - k
                eps = 2 * np.unpackbits(bytes_of(part["eps"]), axis=1, bitorder="little")[:, :d].astype(np.int64) - 1
                v = decode_rows(q, eps, part["lam"].to_numpy(zero_copy_only=False)[:, None], k, basis)[:, :width]
                yield pa.RecordBatch.from_arrays([part["id"], listed(v)], ["id", "v"])

    return messages.mapInArrow(run, "id bigint, v array<double>")


def roundtrip(df: DataFrame, lam: float, k: int = 1, seeds: int = 1, basis: str = "butterfly", id_col: str = "vec_id", col: str = "embedding") -> DataFrame:
    """(id, seed, err_sq, out_sq, top, norm_sq): squared error, squared norm of the output, largest flattened entry."""

    def run(batches):
        for b in batches:
            x, _ = vectors(b["v"])
            ids = b["id"].to_numpy(zero_copy_only=False)
            for s in range(seeds):
                q, eps, z = encode_rows(x, ids, lam, k, s, basis=basis)
                y = decode_rows(q, eps, lam, k, basis)
                cols = [ids, np.full(len(ids), s), ((y - x) ** 2).sum(1), (y * y).sum(1), np.abs(z).max(1) if len(z) else np.zeros(0), (x * x).sum(1)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["id", "seed", "err_sq", "out_sq", "top", "norm_sq"])

    return df.selectExpr(f"cast({id_col} as bigint) id", f"cast({col} as array<double>) v").mapInArrow(run, "id bigint, seed bigint, err_sq double, out_sq double, top double, norm_sq double")
