"""Shared plumbing of the corpus operators: scratch tables, bounded samples, Arrow helpers."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from compresslab.sources.scratch import materialize, scratch_path  # noqa: F401 (the operators take them from here)
from compresslab.sources.shipping import ship


ARROW_ROWS = 500


def small_arrow(spark: SparkSession) -> None:
    """Whole texts cross to Python in batches of at most ARROW_ROWS rows, so that JVM buffers and workers stay small."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    small_arrow(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def hash_unit(*cols: str, seed: int = 0):
    """A number in [0, 1) that depends on the given columns only, never on partitioning."""
    return F.pmod(F.xxhash64(*[F.col(c) for c in cols], F.lit(seed)), F.lit(1 << 40)) / F.lit(float(1 << 40))


def bounded_per_class(df: DataFrame, key: str, id_col: str, bounds: dict, seed: int = 7) -> DataFrame:
    """A reproducible sample of about bounds[value] rows of each of these values of `key` (all, if there are fewer).

    Two narrow passes: class sizes first (one row per class), then a hash threshold per class that
    is evaluated while scanning, so nothing is shuffled or ranked. Only for fitting a model.
    """
    sizes = {r[0]: r[1] for r in df.where(F.col(key).isin(list(bounds))).groupBy(key).count().collect()}
    keep = F.lit(False)
    for value, n in sorted(sizes.items()):
        keep = keep | ((F.col(key) == F.lit(value)) & (hash_unit(id_col, seed=seed) < F.lit(min(1.0, bounds[value] / max(n, 1)))))
    return df.where(keep)


def keep_rows(mask_of: Callable[[pa.RecordBatch], pa.Array]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A mapInArrow function that drops the rows whose mask is false and leaves every column as it is."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield batch.filter(mask_of(batch))

    return run


def small_batches(batch: pa.RecordBatch, text: str, limit: int = 512 << 10) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that a piece holds about `limit` bytes of text at most (or one row)."""
    if batch.num_rows == 0:
        return
    import pyarrow.compute as pc

    sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False)
    start, total = 0, 0
    for i, n in enumerate(sizes):
        if i > start and total + n > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    yield batch.slice(start)


def text_bytes(column: pa.Array):
    """(all bytes as uint8, offsets as int64) of a string column; nulls count as empty."""
    import numpy as np
    import pyarrow.compute as pc

    column = pc.fill_null(column.cast(pa.large_string()), "")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64, count=len(column) + 1 + column.offset)[column.offset :]
    data = column.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


LONG, INT, DOUBLE, STRING, BOOLEAN, BINARY = (T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType(), T.BooleanType(), T.BinaryType())


def schema(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])
