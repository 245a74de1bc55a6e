"""Counter-based randomness: a value depends on its key alone, never on partitions, order or retries.

Three forms. Portable: 60 bits of an md5 over a text key, the same in any SQL engine. Counter: 32 bits of an integer mix
over whole-number keys, vectorised over any shape in the kernels, and as SQL for their oracles. Stream: a Philox
generator for a key, for sampling with other laws.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _key(*parts) -> Column:
    return F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])


def hash60(*parts) -> Column:
    """60 uniform bits as a long out of the parts joined by colons."""
    return F.conv(F.substring(F.md5(_key(*parts)), 1, 15), 16, 10).cast("long")


def rademacher(*parts) -> Column:
    """-1 or +1."""
    return (F.lit(1) - F.lit(2) * (hash60(*parts) % 2)).cast("int")


def uniform_int(width, *parts) -> Column:
    """0 to width-1."""
    return hash60(*parts) % (width if isinstance(width, Column) else F.lit(width))


def hash60_py(*parts) -> int:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def sql_hash60(*parts: str) -> str:
    """The same in DuckDB's SQL; parts are SQL expressions."""
    joined = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"CAST('0x' || substr(md5({joined}), 1, 15) AS BIGINT)"


# Multiplier of the 32-bit mix, increment between key parts, and the numbers of the streams.
MIX, STEP, MASK = 0x45D9F3B, 0x9E3779B1, 0xFFFFFFFF
STREAMS = {"eps-worker": 1, "eps-server": 2, "tau-worker": 3, "tau-server": 4, "keep": 5, "ternary": 6, "coordinate": 7}


def _mix32(h):
    h = ((h ^ (h >> 16)) * MIX) & MASK
    h = ((h ^ (h >> 16)) * MIX) & MASK
    return h ^ (h >> 16)


def counter_hash(*parts) -> np.ndarray:
    """32 uniform bits for each key of whole numbers from 0 below 2^63; arrays broadcast."""
    h = np.zeros((), np.uint64)
    for p in parts:
        p = np.asarray(p, np.int64).astype(np.uint64)
        h = _mix32((h + STEP + (p & np.uint64(MASK))) & np.uint64(MASK))
        if (p >> np.uint64(32)).any():
            high = p >> np.uint64(32)
            h = np.where(high > 0, _mix32((h + STEP + high) & np.uint64(MASK)), h)
    return h


def sql_counter_hash(*parts: str) -> str:
    """The same in DuckDB's SQL for keys below 2^32; parts are SQL expressions."""
    mix = lambda x: f"list_reduce([{x}, 0, 0], lambda h, i: (xor(h, h >> 16) * {MIX}) & {MASK})"
    out = "0::BIGINT"
    for p in parts:
        inner = mix(f"(({out}) + {STEP} + ({p})) & {MASK}")
        out = f"list_transform([{inner}], lambda h: xor(h, h >> 16))[1]"
    return out


def draw_indices(spark: SparkSession, rounds: int, n_workers: int, m_prime: int, m: int, seed: int = 0, first: int = 0) -> DataFrame:
    """(t, worker, slot, row_id) of ``rounds`` rounds from ``first`` on: uniform draws with replacement from 0..m-1,
    generated in the executors. A draw depends on its round alone, so those of earlier rounds are never made."""
    if m < 1:
        raise ValueError("no rows to draw from")
    per = n_workers * m_prime
    ids = spark.range(first * per, (first + rounds) * per)
    t = F.floor(F.col("id") / (n_workers * m_prime)).cast("int")
    worker = F.floor(F.col("id") / m_prime).cast("long") % n_workers
    out = ids.select(t.alias("t"), worker.cast("int").alias("worker"), (F.col("id") % m_prime).cast("int").alias("slot"))
    return out.withColumn("row_id", uniform_int(m, seed, "draw", F.col("t"), F.col("worker"), F.col("slot")))


def stream(seed: int, name: str, *counters: int) -> np.random.Generator:
    """An independent generator for each key."""
    raw = hashlib.blake2b(":".join(map(str, (seed, name, *counters))).encode(), digest_size=16).digest()
    return np.random.Generator(np.random.Philox(key=np.frombuffer(raw, np.uint64)))
