"""Vectorised functions for SQL users: scalar, aggregate and table functions over Arrow or pandas batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import rounding, vectors


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def float_round(vec: pd.Series, form: pd.Series) -> pd.Series:
    """A vector in the values that a low-precision format keeps."""
    return pd.Series([None if v is None else rounding.round_array(np.asarray(v, dtype=np.float64), f).tolist() for v, f in zip(vec, form)])


@F.pandas_udf(T.DoubleType())
def cosine_of(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        size = np.linalg.norm(x) * np.linalg.norm(y)
        return float(np.dot(x, y) / size) if size > 0 else 0.0

    return pd.Series([None if x is None or y is None else one(np.asarray(x, float), np.asarray(y, float)) for x, y in zip(a, b)], dtype="float64")


@F.pandas_udf(T.BinaryType())
def pack_bits(vec: pd.Series) -> pd.Series:
    return pd.Series([None if v is None else np.packbits(np.asarray(v) > 0).tobytes() for v in vec])


@F.pandas_udf(T.IntegerType())
def hamming_of(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([int(np.bitwise_count(np.bitwise_xor(np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8))).sum()) for x, y in zip(a, b)], dtype="int32")


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_mean(vec: pd.Series) -> list:
    """Aggregate: the mean vector of a group."""
    return np.mean(np.stack(vec.to_numpy()).astype(np.float64), axis=0).tolist()


@F.udtf(returnType=T.StructType([T.StructField("bin", T.IntegerType()), T.StructField("low", T.DoubleType()), T.StructField("high", T.DoubleType())]))
class ExplodeBins:
    """Table function: the equal-width bins between two values."""

    def eval(self, low: float, high: float, bits: int):
        n = 2**bits
        for i in range(n):
            yield i, low + (high - low) * i / n, low + (high - low) * (i + 1) / n


def mean_vectors(df, keys: tuple[str, ...], vec_col: str):
    """keys..., pos, mean: vector means that combine before the shuffle; one row of sums a task and key."""
    kinds = dict(df.dtypes)

    def run(batches: Iterator[pa.RecordBatch]):
        held: dict = {}
        for b in batches:
            x = vectors.matrix(b.column(len(keys)))
            for i, key in enumerate(zip(*(b.column(j).to_pylist() for j in range(len(keys))))):
                total = held.setdefault(key, [np.zeros(x.shape[1]), 0])
                total[0] += x[i]
                total[1] += 1
        for key, (total, n) in held.items():
            d = len(total)
            yield pa.RecordBatch.from_arrays([*(pa.array([k] * d, b.schema.field(j).type) for j, k in enumerate(key)), pa.array(np.arange(d, dtype=np.int32)), pa.array(total), pa.array(np.full(d, n))], names=[*keys, "pos", "total", "n"])

    part = df.select(*keys, vec_col).mapInArrow(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", pos int, total double, n long")
    return part.groupBy(*keys, "pos").agg((F.sum("total") / F.sum("n")).alias("mean"))


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    for name, f in (("float_round", float_round), ("cosine_of", cosine_of), ("pack_bits", pack_bits), ("hamming_of", hamming_of), ("vector_mean", vector_mean)):
        spark.udf.register(name, f)
    spark.udtf.register("explode_bins", ExplodeBins)
