"""The whole evaluation: calibrate, encode, search all codecs and tiers in one scan, measure, test, report."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import calibrate, codecs, metrics, search, significance
from . import grids


def calibrated(vectors: DataFrame, wanted: list[codecs.Codec], vec_col: str = "embedding", id_col: str = "vec_id", method: str = "kll", pq_rounds: int = 25):
    """(codec, calibration) of every codec: quantiles in one pass, principal directions in another, one training per PQ.

    method: `kll` merges sketches of a bounded size and is the way for large tables; `exact` holds all distinct values of a
    dimension in one aggregation buffer and is for checks.
    """
    levels = sorted({level for c in wanted for level in c.levels()})
    base = calibrate.quantiles(vectors, levels or (0.5,), vec_col, method)
    principal = calibrate.principal(vectors, vec_col) if any(isinstance(c, codecs.Pca) for c in wanted) else None
    books: dict = {}
    out = []
    for c in wanted:
        if isinstance(c, codecs.Pca):
            out.append((c, principal))
        elif isinstance(c, codecs.Pq):
            key = (c.m, c.width)
            if key not in books:
                books[key] = codecs.train_pq(vectors, c.m, c.width, pq_rounds, id_col, vec_col)
            out.append((c, books[key]))
        else:
            out.append((c, base))
    return out


def ratios(variants, dims: int, native: int = 32) -> dict[str, float]:
    return {c.name: c.ratio(dims, native) for c, _ in variants}


def ratio_column(found: dict[str, float], name: str = "variant"):
    return F.element_at(F.create_map(*(F.lit(x) for kv in found.items() for x in kv)), F.col(name))


def evaluate(queries: tuple[np.ndarray, np.ndarray], items: DataFrame, qrels: DataFrame, variants, ks=(10, 100), k: int = 100, tiers: int = 1, **columns) -> DataFrame:
    """variant, tier, query_id, metric, k, value from one scan of the items."""
    run = search.topk_fused(queries, items, variants, k, tiers, **columns)
    return metrics.evaluate(run, qrels, ks, ("variant", "tier"), known=[(c.name, t) for c, _ in variants for t in range(1, tiers + 1)])


def significance_of(values: DataFrame, metric: str = "recall", k: int = 100, keys: tuple[str, ...] = ("tier",)) -> DataFrame:
    """Pairs (variant, keys..., base, other) of every codec with the uncompressed vectors, query by query."""
    own = values.where((F.col("metric") == metric) & (F.col("k") == k))
    base = own.where("variant = 'identity'").select(*keys, "query_id", F.col("value").alias("base"))
    return own.where("variant != 'identity'").join(base, [*keys, "query_id"]).select("variant", *keys, "base", F.col("value").alias("other"))


def stars(values: DataFrame, metric: str = "recall", k: int = 100) -> DataFrame:
    return significance.with_z(significance.statistic(significance_of(values, metric, k), ("variant", "tier")))


def grid(vectors: DataFrame, queries, qrels: DataFrame, dims: int, wanted=None, method: str = "kll", **more) -> DataFrame:
    """variant, ratio, metric, k, value: the means of every cell of a grid."""
    variants = calibrated(vectors, wanted or grids.full(dims), method=method)
    values = metrics.summary(evaluate(queries, vectors, qrels, variants, **more), ("variant",))
    return values.withColumn("ratio", F.round(ratio_column(ratios(variants, dims)), 6))
