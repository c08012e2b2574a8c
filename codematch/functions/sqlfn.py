"""The methods as functions for SQL: scalar, aggregate and table functions over Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from codematch.operators.encode import fine_column
from codematch.operators.model import CodeModel


def encode_udf(model: CodeModel):
    """vec -> struct(c1, c2, fine); null for a null vector."""

    @F.arrow_udf(T.StructType([T.StructField("c1", T.IntegerType()), T.StructField("c2", T.IntegerType()), T.StructField("fine", T.ArrayType(T.ShortType()))]))
    def encode(vecs: pa.Array) -> pa.Array:
        ok = np.array(vecs.is_valid())
        out = [None] * len(vecs)
        if ok.any():
            x = np.array([v for v in vecs.to_pylist() if v is not None], float)
            c, f = model.encode(x)
            rows = zip(c[:, 0].tolist(), c[:, 1].tolist() if model.halves == 2 else [None] * len(c), fine_column(f).to_pylist(), strict=True)
            for i, (c1, c2, fine) in zip(np.flatnonzero(ok), rows, strict=True):
                out[i] = {"c1": c1, "c2": c2, "fine": fine}
        return pa.array(out, pa.struct([("c1", pa.int32()), ("c2", pa.int32()), ("fine", pa.list_(pa.int16()))]))

    return encode


@F.arrow_udf(T.IntegerType())
def hits_udf(a: pa.Array, b: pa.Array) -> pa.Array:
    """Number of equal fine codes."""
    return pa.array([None if x is None or y is None else sum(p == q for p, q in zip(x, y, strict=False)) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.int32())


@F.arrow_udf(T.ArrayType(T.LongType()))
def tokens_udf(c1: pa.Array, c2: pa.Array, fine: pa.Array) -> pa.Array:
    """Packed tokens of a code."""
    out = []
    for x, y, f in zip(c1.to_pylist(), c2.to_pylist(), fine.to_pylist(), strict=True):
        out.append(None if f is None else [((x if y is None or p < len(f) // 2 else y) << 32) | (p << 16) | v for p, v in enumerate(f)])
    return pa.array(out, pa.list_(pa.int64()))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_mean(v: pd.Series) -> list:
    """Mean of a group's vectors: for groups that fit a task; kmeans and prep add up partial sums instead."""
    return np.mean(np.stack(v.to_list()), axis=0).tolist()


@F.udtf(returnType=T.StructType([T.StructField("token", T.LongType()), T.StructField("position", T.IntegerType())]))
class FlattenCodes:
    """(c1, c2, fine) -> one row per position."""

    def eval(self, c1: int, c2: int, fine: list):
        for p, f in enumerate(fine or []):
            yield ((c1 if c2 is None or p < len(fine) // 2 else c2) << 32) | (p << 16) | f, p


def register(spark: SparkSession, model: CodeModel) -> None:
    """ccm_encode, ccm_hits, ccm_tokens and the table function flatten_codes for SQL text."""
    spark.udf.register("ccm_encode", encode_udf(model))
    spark.udf.register("ccm_hits", hits_udf)
    spark.udf.register("ccm_tokens", tokens_udf)
    spark.udtf.register("flatten_codes", FlattenCodes)
