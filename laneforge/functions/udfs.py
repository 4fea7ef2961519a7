"""Functions for SQL: encode and decode arrays, sizes, an aggregate, a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .codecs import ALL

STRIDES = {"d1": 1, "s4": 4, "none": 0}


def _deltas(values, delta: str) -> np.ndarray:
    x = np.asarray(values, np.int64)
    return (K.delta(x, STRIDES[delta]) if STRIDES[delta] else x).astype(np.uint64)


@F.pandas_udf(T.BinaryType())
def encode_ints(values: pd.Series, codec: pd.Series, delta: pd.Series) -> pd.Series:
    return pd.Series([None if v is None else ALL[c].encode(_deltas(v, d)) for v, c, d in zip(values, codec, delta)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def decode_ints(payload: pd.Series, n: pd.Series, codec: pd.Series, delta: pd.Series) -> pd.Series:
    out = []
    for p, k, c, d in zip(payload, n, codec, delta):
        if p is None:
            out.append(None)
            continue
        v = ALL[c].decode(bytes(p), int(k)).astype(np.int64)
        out.append(K.undelta(v, STRIDES[d]) if STRIDES[d] else v)
    return pd.Series(out)


@F.pandas_udf(T.LongType())
def codec_size(values: pd.Series, codec: pd.Series, delta: pd.Series) -> pd.Series:
    return pd.Series([None if v is None else len(ALL[c].encode(_deltas(v, d))) for v, c, d in zip(values, codec, delta)], dtype="Int64")


def pack_agg(x: Column, codec: str = "vpack128", delta: str = "d1") -> Column:
    """Aggregate: the encoded ids of a group. For groups that fit a task; chunk larger ones first."""
    return encode_ints(F.array_sort(F.collect_set(x)), F.lit(codec), F.lit(delta))


@F.udtf(returnType=T.StructType().add("block_no", T.IntegerType()).add("pos", T.IntegerType()).add("x", T.LongType()))
class UnpackBlocks:
    """unpack_blocks(payload, n, codec, delta, lo, hi): the ids of a payload in [lo, hi], with their block of 128 and place."""

    def eval(self, payload: bytes, n: int, codec: str, delta: str, lo: int, hi: int):
        if payload is None:
            return
        v = ALL[codec].decode(bytes(payload), n).astype(np.int64)
        x = K.undelta(v, STRIDES[delta]) if STRIDES[delta] else v
        for i in np.flatnonzero((x >= lo) & (x <= hi)).tolist():
            yield i // 128, i, int(x[i])


def register(spark: SparkSession) -> None:
    """Makes encode_ints, decode_ints, codec_size and unpack_blocks known to SQL."""
    for name, f in (("encode_ints", encode_ints), ("decode_ints", decode_ints), ("codec_size", codec_size)):
        spark.udf.register(name, f)
    spark.udtf.register("unpack_blocks", UnpackBlocks)
