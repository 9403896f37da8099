"""Generated unit vectors: a Python data source whose rows depend on their id alone."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FIRST_ID, BLOCK = 10**9, 4096


def block_vectors(block: int, dims: int, seed: int) -> np.ndarray:
    """The unit vectors of ids block * BLOCK onwards; the block number is the generator's counter."""
    rng = np.random.Generator(np.random.Philox(key=[seed, block]))
    x = rng.standard_normal((BLOCK, dims)).astype(np.float32)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.dims = int(options.get("rows", BLOCK)), int(options.get("dims", 64))
        self.seed, self.slices = int(options.get("seed", 1)), int(options.get("slices", 8))

    def partitions(self):
        blocks = -(-self.rows // BLOCK)
        each = -(-blocks // max(1, min(self.slices, blocks)))
        return [InputPartition((b, min(b + each, blocks))) for b in range(0, blocks, each)]

    def read(self, partition):
        for block in range(*partition.value):
            x = block_vectors(block, self.dims, self.seed)[: self.rows - block * BLOCK]
            ids = FIRST_ID + block * BLOCK + np.arange(len(x))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * self.dims), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(ids), lists], names=["vec_id", "embedding"])


class SyntheticVectors(DataSource):
    """spark.read.format("synthetic_vectors").option("rows", n).option("dims", d)"""

    @classmethod
    def name(cls):
        return "synthetic_vectors"

    def schema(self):
        return "vec_id long, embedding array<float>"

    def reader(self, schema):
        return _Reader(self.options)


def synthetic_vectors(spark: SparkSession, rows: int, dims: int = 64, seed: int = 1, slices: int = 8) -> DataFrame:
    spark.dataSource.register(SyntheticVectors)
    return spark.read.format("synthetic_vectors").options(rows=rows, dims=dims, seed=seed, slices=slices).load()
