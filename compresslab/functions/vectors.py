"""Vectors as arrays: Column functions over them, and moves between arrays, long rows and numpy matrices."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Cosine; 0 where a norm is 0."""
    size = norm(a) * norm(b)
    return F.when(size > 0, dot(a, b) / size).otherwise(0.0)


def sound(vec: Column) -> Column:
    """True for vectors without nulls and with finite values only."""
    return F.coalesce(vec.isNotNull() & F.forall(vec, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))), F.lit(False))


def sign_bits(vec: Column, thresholds: Column | None = None) -> Column:
    """A string of 0 and 1: 1 where the value is above 0, or above the threshold of its dimension."""
    above = F.transform(vec, lambda v: (v > 0).cast("int").cast("string")) if thresholds is None else F.zip_with(vec, thresholds, lambda v, t: (v.cast("double") > t).cast("int").cast("string"))
    return F.array_join(above, "")


def pack_words(bits: Column, n: int) -> Column:
    """array<long> of 63 bits a word from a string of n bits; Hamming distance is bit_count over the words' xor."""
    return F.array(*(F.conv(F.substring(bits, i + 1, min(63, n - i)), 2, 10).cast("long") for i in range(0, n, 63)))


def hamming(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def common_ones(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseAND(y))), F.lit(0), lambda s, x: s + x)


def ones(a: Column) -> Column:
    return F.aggregate(F.transform(a, lambda x: F.bit_count(x)), F.lit(0), lambda s, x: s + x)


def long_rows(df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """id, pos, v: one row a dimension. For statistics and checks; scoring stays on arrays."""
    return df.select(id_col, F.posexplode(vec_col).alias("pos", "v")).select(id_col, "pos", F.col("v").cast("double").alias("v"))


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """The rows of a list column as a float64 matrix, without a Python object per row."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.list_(pa.float64()))
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1).astype(np.float64) if len(column) else np.zeros((0, 0))


def lists(x: np.ndarray, kind: pa.DataType = pa.float64()) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x).ravel(), kind))
