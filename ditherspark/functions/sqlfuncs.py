"""SQL functions of the codec: ``register(spark)``, then for example ``SELECT ds_encode(embedding, 0.51D, 7, vec_id)``.

Scalars take Arrow batches; ``ds_vector_sum`` aggregates arrays; ``ds_unpack_rows`` is a table function over one message.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ditherspark.operators.basis import BASES
from ditherspark.operators.codec import decode_rows, encode_rows, padded, signs
from ditherspark.operators.quantize import pack_levels, unpack_levels

DOUBLES, INTS = T.ArrayType(T.DoubleType()), T.ArrayType(T.IntegerType())


@pandas_udf(DOUBLES)
def ds_flatten(v: pd.Series, key: pd.Series) -> pd.Series:
    x = padded(list(v))
    return pd.Series(list(BASES["butterfly"].forward(x * signs(0, "worker", 0, key.to_numpy(), x.shape[1]))))


@pandas_udf(DOUBLES)
def ds_unflatten(z: pd.Series, key: pd.Series) -> pd.Series:
    x = padded(list(z))
    return pd.Series(list(BASES["butterfly"].adjoint(x) * signs(0, "worker", 0, key.to_numpy(), x.shape[1])))


@pandas_udf(INTS)
def ds_encode(v: pd.Series, lam: pd.Series, k: pd.Series, key: pd.Series) -> pd.Series:
    x = padded(list(v))
    return pd.Series([encode_rows(x[i : i + 1], np.array([key.iloc[i]]), float(lam.iloc[i]), int(k.iloc[i]), 0)[0][0].astype(np.int32) for i in range(len(x))])


@pandas_udf(DOUBLES)
def ds_decode(q: pd.Series, lam: pd.Series, k: pd.Series, key: pd.Series) -> pd.Series:
    out = []
    for levels, a, n, i in zip(q, lam, k, key, strict=True):
        levels = np.asarray(levels)[None]
        out.append(decode_rows(levels, signs(0, "worker", 0, np.array([i]), levels.shape[1]), float(a), int(n))[0])
    return pd.Series(out)


@pandas_udf(T.BinaryType())
def ds_pack(q: pd.Series, k: pd.Series) -> pd.Series:
    return pd.Series([pack_levels(np.asarray(a)[None], int(n))[0] for a, n in zip(q, k, strict=True)])


@pandas_udf(INTS)
def ds_unpack(b: pd.Series, k: pd.Series, d: pd.Series) -> pd.Series:
    return pd.Series([unpack_levels([a], int(n), int(m))[0].astype(np.int32) for a, n, m in zip(b, k, d, strict=True)])


@pandas_udf(DOUBLES)
def ds_vector_sum(v: pd.Series) -> list:
    """Sum of a group's arrays. It sees a whole group: aggregate by task or block before large groups."""
    return np.sum(np.stack(v.to_numpy()), axis=0).tolist()


@udtf(returnType=T.StructType([T.StructField("coord", T.IntegerType()), T.StructField("q", T.IntegerType())]))
class ds_unpack_rows:  # noqa: N801
    """(coord, q) of one packed message."""

    def eval(self, packed: bytes, k: int, d: int):
        for i, q in enumerate(unpack_levels([packed], k, d)[0].tolist()):
            yield i, q


def register(spark: SparkSession) -> None:
    functions = {"ds_flatten": ds_flatten, "ds_unflatten": ds_unflatten, "ds_encode": ds_encode, "ds_decode": ds_decode, "ds_pack": ds_pack, "ds_unpack": ds_unpack, "ds_vector_sum": ds_vector_sum}
    for name, f in functions.items():
        spark.udf.register(name, f)
    spark.udtf.register("ds_unpack_rows", ds_unpack_rows)
