"""Vectors as a stream: encode micro-batches with a frozen calibration, keep a running top-k, watch drift.

The micro-batch is the batch of the method: it may carry its own thresholds. Output is written once per batch number, so
a retried batch overwrites itself. Late vectors simply merge, since a top-k does not depend on the order.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import calibrate, codecs, search
from ..sources.scratch import scratch_path


def vector_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A stream of vec_id and embedding from a parquet table."""
    return spark.readStream.schema("vec_id long, embedding array<float>, label int").option("maxFilesPerTrigger", files).parquet(path)


def replay(vectors: DataFrame, batches: int) -> str:
    """Write a table as `batches` files that a stream reads one after the other."""
    path = scratch_path(vectors.sparkSession, "replay")
    for i in range(batches):
        vectors.where(F.pmod("vec_id", F.lit(batches)) == i).coalesce(1).write.mode("append").parquet(path)
    return path


def encode_stream(stream: DataFrame, codec: codecs.Codec, frozen: calibrate.Calibration | None, out: str) -> None:
    """Append codes under out, one folder for each micro-batch; without `frozen` each batch learns its own thresholds."""

    def write(batch: DataFrame, number: int):
        c = frozen or calibrate.quantiles(batch, codec.levels() or (0.5,))
        codecs.encode(batch, codec, c).write.mode("overwrite").parquet(f"{out}/batch_id={number}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", scratch_path(stream.sparkSession, "stream")).trigger(availableNow=True).start().awaitTermination()


def running_topk(stream: DataFrame, queries, k: int, out: str) -> None:
    """Keep each query's k best over all micro-batches in the state store; each change is written under out."""
    partial = search._scan(queries, stream, [(codecs.identity(), calibrate.Calibration())], k, "vec_id", "embedding", None, None)

    def update(key, frames, state):
        held = [pd.DataFrame({"item_id": state.get[0], "score": state.get[1]})] if state.exists else []
        best = pd.concat([*held, *(f[["item_id", "score"]] for f in frames)]).sort_values(["score", "item_id"], ascending=[False, True]).head(k)
        state.update(([int(i) for i in best["item_id"]], [float(s) for s in best["score"]]))
        yield pd.DataFrame({"query_id": key[0], "item_id": best["item_id"].astype("int64"), "rank": range(1, len(best) + 1), "score": best["score"]})

    found = partial.select("query_id", "item_id", "score").groupBy("query_id").applyInPandasWithState(
        update, "query_id long, item_id long, rank int, score double", "items array<long>, scores array<double>", "update", "NoTimeout")

    def write(batch: DataFrame, number: int):
        batch.write.mode("overwrite").parquet(f"{out}/batch_id={number}")

    found.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", scratch_path(stream.sparkSession, "stream")).trigger(availableNow=True).start().awaitTermination()


def latest(spark: SparkSession, out: str) -> DataFrame:
    """The running top-k's last state of every query."""
    rows = spark.read.parquet(out)
    last = F.max("batch_id").over(Window.partitionBy("query_id"))
    return rows.withColumn("last", last).where("batch_id = last").drop("last", "batch_id")


def drift(vectors: DataFrame, batch_col: str, level: float = 0.5, method: str = "kll") -> DataFrame:
    """batch, moved: mean distance of a batch's thresholds from those of all batches."""
    per = calibrate.quantile_rows(vectors, (level,), (batch_col,), method=method).select(batch_col, "pos", F.col("q")[0].alias("own"))
    every = calibrate.quantile_rows(vectors, (level,), method=method).select("pos", F.col("q")[0].alias("all"))
    return per.join(F.broadcast(every), "pos").groupBy(batch_col).agg(F.avg(F.abs(F.col("own") - F.col("all"))).alias("moved"))
