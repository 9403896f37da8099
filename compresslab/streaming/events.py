"""Windows over events, each as a declarative plan that runs on a bounded table and on a stream alike.

On a stream, `late` is how far rows may lag behind the newest one; the watermark drops later ones and bounds the state.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.scratch import scratch_path
from ..sources.tables import SCHEMAS


def tumbling(events: DataFrame, size: str = "1 hour", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 6).alias("total")).select(F.col("w.start").alias("window_start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "1 hour", step: str = "30 minutes", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n"), F.round(F.max("value"), 6).alias("top")).select(F.col("w.start").alias("window_start"), "n", "top")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("session_start"), "n")


def as_of(left: DataFrame, right: DataFrame, by: str, left_ts: str, right_ts: str, value: str) -> DataFrame:
    """left with the last `value` of right at or before each row's time, per `by`: union and a running last, one shuffle."""
    both = left.select(by, F.col(left_ts).alias("__t"), F.lit(1).alias("__side"), F.struct(*left.columns).alias("__row"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__v")).unionByName(
        right.select(by, F.col(right_ts).alias("__t"), F.lit(0).alias("__side"), F.lit(None).cast(left.select(F.struct(*left.columns)).dtypes[0][1]).alias("__row"), F.col(value).alias("__v")))
    w = Window.partitionBy(by).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("__v", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").select("__row.*", F.col("__v").alias(f"as_of_{value}"))


def interval_join(left: DataFrame, right: DataFrame, by: str, seconds: int) -> DataFrame:
    """Pairs of left and right rows of one key with right.ts within `seconds` after left.ts, by time buckets.

    A row meets only the rows of its own bucket and the next one, so a busy key is spread over time.
    """
    t = lambda c: F.unix_micros(c.cast("timestamp"))
    wide = seconds * 1_000_000
    l = left.select(by, F.col("event_id").alias("left_id"), t(F.col("ts")).alias("lt"))  # noqa: E741
    r = right.select(F.col(by).alias("rk"), F.col("event_id").alias("right_id"), t(F.col("ts")).alias("rt"))
    l = l.withColumn("bucket", F.explode(F.array(F.floor(F.col("lt") / wide), F.floor(F.col("lt") / wide) + 1)))  # noqa: E741
    r = r.withColumn("rbucket", F.floor(F.col("rt") / wide))
    return l.join(r, (F.col(by) == F.col("rk")) & (F.col("bucket") == F.col("rbucket"))).where((F.col("rt") > F.col("lt")) & (F.col("rt") <= F.col("lt") + wide)).select(by, "left_id", "right_id")


def interval_stream(left: DataFrame, right: DataFrame, by: str, span: str, late: str) -> DataFrame:
    """The same pairs from two streams: each side's rows wait in the state store until the watermark passes the span."""
    l = left.withWatermark("ts", late).select(by, F.col("event_id").alias("left_id"), F.col("ts").alias("lt"))  # noqa: E741
    r = right.withWatermark("ts", late).select(F.col(by).alias("rk"), F.col("event_id").alias("right_id"), F.col("ts").alias("rt"))
    return l.join(r, F.expr(f"{by} = rk AND rt > lt AND rt <= lt + INTERVAL {span}")).select(by, "left_id", "right_id")


def replay_in_order(events: DataFrame, chunks: int) -> str:
    """Write events as `chunks` files of equal spans of time, oldest first, for a stream to read one after the other."""
    path = scratch_path(events.sparkSession, "events")
    micros = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)")
    low, high = events.agg(F.min(micros), F.max(micros)).first()
    for i in range(chunks if low is not None else 0):
        part = F.least(F.lit(chunks - 1), F.floor((micros - low) * chunks / (high - low + 1)))
        events.where(part == i).coalesce(1).write.mode("append").parquet(path)
    return path


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """Events with ts as an instant, since a watermark needs one: the clock of the table is read as UTC, whatever the session's zone."""
    e = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files).parquet(path)
    return e.withColumn("ts", F.expr("TIMESTAMP'1970-01-01 00:00:00Z' + (ts - TIMESTAMP_NTZ'1970-01-01 00:00:00')"))


def by_clock(df: DataFrame) -> DataFrame:
    """Instants back to the clock of the table."""
    back = lambda c: F.expr(f"TIMESTAMP_NTZ'1970-01-01 00:00:00' + ({c} - TIMESTAMP'1970-01-01 00:00:00Z')")
    return df.select(*(back(c).alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes))


def drain(found: DataFrame, out: str, mode: str) -> None:
    """Run a streaming plan over all that is there; each micro-batch's rows go to a folder of its own, so a retry overwrites itself."""

    def write(batch: DataFrame, number: int):
        batch.write.mode("overwrite").parquet(f"{out}/batch_id={number}")

    stream = found.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", scratch_path(found.sparkSession, "stream"))
    stream.trigger(availableNow=True).start().awaitTermination()


def over_stream(events: DataFrame, plan: Callable[[DataFrame], DataFrame], keys: tuple[str, ...], chunks: int = 4) -> DataFrame:
    """plan(stream of events) in update mode: the last state of every keys value."""
    spark = events.sparkSession
    out = scratch_path(spark, "windows")
    drain(plan(event_stream(spark, replay_in_order(events, chunks))), out, "update")
    rows = by_clock(spark.read.parquet(out))
    values = F.struct(*(c for c in rows.columns if c != "batch_id"))
    return rows.groupBy(*keys).agg(F.max_by(values, "batch_id").alias("r")).select("r.*")
