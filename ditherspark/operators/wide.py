"""Transforms and means of vectors too long for one row: coordinates live in blocks, and one shuffle transposes them.

The index of a coordinate splits in (hi, lo). Each block first transforms its lo part by itself; after the transpose each
row holds one lo and transforms over hi. Two local passes and one exchange take the place of log2 d exchanges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.operators.basis import butterfly_expr


def to_blocks(long: DataFrame, lo_bits: int, value: str = "x") -> DataFrame:
    """(hi, a): (coord, value) rows as zero-filled arrays of 2^lo_bits longs."""
    size = 1 << lo_bits
    pairs = long.groupBy(F.shiftright("coord", lo_bits).alias("hi"), F.col("coord").bitwiseAND(F.lit(size - 1)).cast("int").alias("lo")).agg(F.sum(value).alias("v"))
    held = pairs.groupBy("hi").agg(F.map_from_entries(F.collect_list(F.struct("lo", "v"))).alias("m"))  # at most 2^lo_bits entries
    return held.select("hi", F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long"))).alias("a"))


def wide_butterfly(blocks: DataFrame, hi_bits: int, lo_bits: int) -> DataFrame:
    """(lo, z): the unnormalised transform of all 2^(hi_bits+lo_bits) coordinates, z[hi] the entry of (hi, lo). Missing
    blocks count as zero."""
    size = 1 << hi_bits
    local = blocks.select("hi", F.posexplode(butterfly_expr(F.col("a"), 1 << lo_bits)).alias("lo", "v"))
    turned = local.groupBy("lo").agg(F.map_from_entries(F.collect_list(F.struct(F.col("hi").cast("int"), "v"))).alias("m"))  # at most 2^hi_bits
    filled = F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long")))
    return turned.select("lo", butterfly_expr(filled, size).alias("z"))


def wide_long(turned: DataFrame, lo_bits: int) -> DataFrame:
    """(coord, z) rows of ``wide_butterfly``."""
    rows = turned.select("lo", F.posexplode("z").alias("hi", "z"))
    return rows.select((F.col("hi") * (1 << lo_bits) + F.col("lo")).cast("long").alias("coord"), "z")
