"""Ranking measures per query, cutoff and any grouping keys; distortion and overlap of codecs; sizes.

Queries without a single hit keep their rows: every (keys, query) that exists among the keys and the judged
queries is scored. Judgments are a stated small set and are broadcast by Spark below its own threshold.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

CUTOFFS = (1, 3, 5, 10, 20, 50, 100, 1000)


def ideal(qrels: DataFrame, ks, gain: str = "linear") -> DataFrame:
    """query_id, relevant, idcg_<k>..."""
    order = Window.partitionBy("query_id").orderBy(F.desc("grade"))
    worth = F.pow(F.lit(2.0), "grade") - 1 if gain == "exp2" else F.col("grade").cast("double")
    placed = qrels.where("grade > 0").withColumn("place", F.row_number().over(order)).withColumn("part", worth / F.log2(F.col("place") + 1.0))
    return placed.groupBy("query_id").agg(F.count("*").alias("relevant"), *(F.sum(F.when(F.col("place") <= k, F.col("part"))).alias(f"idcg_{k}") for k in ks))


def _frame(run: DataFrame, keys: tuple[str, ...], known) -> DataFrame:
    """The values of keys: as told, or those in the run, which then is computed once more unless it is a written table."""
    if known is None:
        return run.select(*keys).distinct()
    return F.broadcast(run.sparkSession.createDataFrame(known, run.select(*keys).schema))


def evaluate(run: DataFrame, qrels: DataFrame, ks=CUTOFFS, keys: tuple[str, ...] = (), gain: str = "linear", known: list[tuple] | None = None) -> DataFrame:
    """keys..., query_id, metric (recall, ndcg, mrr), k, value from run(keys..., query_id, item_id, rank).

    known: all values of keys, where the caller can tell; a run that is not written is then read once only.
    """
    ks = tuple(ks)
    judged = qrels.where("grade > 0").select("query_id", "item_id", "grade")
    worth = F.pow(F.lit(2.0), "grade") - 1 if gain == "exp2" else F.col("grade").cast("double")
    sums = []
    for k in ks:
        hit = F.col("rank") <= k
        sums += [
            F.count(F.when(hit, 1)).alias(f"hits_{k}"),
            F.sum(F.when(hit, F.col("worth") / F.log2(F.col("rank") + 1.0)).otherwise(0.0)).alias(f"dcg_{k}"),
            F.min(F.when(hit, F.col("rank"))).alias(f"first_{k}"),
        ]
    hits = run.join(judged, ["query_id", "item_id"]).withColumn("worth", worth).groupBy(*keys, "query_id").agg(*sums)
    frame = ideal(judged, ks, gain)
    if keys:
        frame = _frame(run, keys, known).crossJoin(frame)
    table = frame.join(hits, [*keys, "query_id"], "left")
    values = []
    for k in ks:
        values += [
            F.struct(F.lit("recall").alias("metric"), F.lit(k).alias("k"), (F.coalesce(f"hits_{k}", F.lit(0)) / F.col("relevant")).alias("value")),
            F.struct(F.lit("ndcg").alias("metric"), F.lit(k).alias("k"), (F.coalesce(f"dcg_{k}", F.lit(0.0)) / F.col(f"idcg_{k}")).alias("value")),
            F.struct(F.lit("mrr").alias("metric"), F.lit(k).alias("k"), F.coalesce(F.lit(1.0) / F.col(f"first_{k}"), F.lit(0.0)).alias("value")),
        ]
    return table.select(*keys, "query_id", F.explode(F.array(*values)).alias("r")).select(*keys, "query_id", "r.metric", "r.k", F.round("r.value", 9).alias("value"))


def recall(run, qrels, ks=CUTOFFS, keys=()) -> DataFrame:
    return evaluate(run, qrels, ks, keys).where("metric = 'recall'")


def ndcg(run, qrels, ks=CUTOFFS, keys=(), gain: str = "linear") -> DataFrame:
    return evaluate(run, qrels, ks, keys, gain).where("metric = 'ndcg'")


def mrr(run, qrels, ks=CUTOFFS, keys=()) -> DataFrame:
    return evaluate(run, qrels, ks, keys).where("metric = 'mrr'")


def summary(values: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys..., metric, k, value: means over queries in percent."""
    return values.groupBy(*keys, "metric", "k").agg(F.round(F.avg("value") * 100, 9).alias("value"))


def macro(values: DataFrame, keys: tuple[str, ...], by: str = "dataset") -> DataFrame:
    """Mean over datasets of the means over queries: every dataset weighs the same."""
    each = values.groupBy(by, *keys, "metric", "k").agg(F.avg("value").alias("value"))
    return each.groupBy(*keys, "metric", "k").agg(F.round(F.avg("value") * 100, 9).alias("value"))


def overlap(run: DataFrame, exact: DataFrame, k: int, keys: tuple[str, ...], known: list[tuple] | None = None) -> DataFrame:
    """keys..., query_id, overlap: share of the exact top k that a run's top k holds."""
    top = exact.where(F.col("rank") <= k).select("query_id", "item_id")
    base = _frame(run, keys, known).crossJoin(top.groupBy("query_id").agg(F.count("*").alias("n")))
    both = run.where(F.col("rank") <= k).join(top, ["query_id", "item_id"]).groupBy(*keys, "query_id").agg(F.count("*").alias("same"))
    return base.join(both, [*keys, "query_id"], "left").select(*keys, "query_id", F.round(F.coalesce("same", F.lit(0)) / F.col("n"), 9).alias("overlap"))


def distortion(items: DataFrame, variants, vec_col: str = "embedding") -> DataFrame:
    """codec, mse, cosine_error: how far decoded vectors are from native ones, summed in one scan."""
    import numpy as np
    import pyarrow as pa

    from ..functions import vectors as V

    shared = items.sparkSession.sparkContext.broadcast(variants)

    def run(batches):
        for b in batches:
            x = V.matrix(b.column(0))
            if not len(x):
                continue
            rows = []
            for codec, c in shared.value:
                y = codec.decode(codec.encode(x, c), c)
                if y.shape[1] < x.shape[1]:
                    y = np.pad(y, ((0, 0), (0, x.shape[1] - y.shape[1])))
                if y.shape[1] != x.shape[1]:
                    continue
                size = np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1)
                cos = np.divide((x * y).sum(axis=1), size, out=np.zeros(len(x)), where=size > 0)
                rows.append((codec.name, float(((x - y) ** 2).sum()), x.size, float((1 - cos).sum()), len(x)))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=["codec", "se", "values", "ce", "n"])

    parts = items.select(vec_col).mapInArrow(run, "codec string, se double, values long, ce double, n long")
    return parts.groupBy("codec").agg((F.sum("se") / F.sum("values")).alias("mse"), (F.sum("ce") / F.sum("n")).alias("cosine_error"))


def index_bytes(n: int, dims: int, variants, native: int = 32) -> list[tuple[str, float, int]]:
    """(codec, ratio, bytes of n codes)."""
    return [(c.name, c.ratio(dims, native), -(-c.bits(dims, native) // 8) * n) for c in variants]
