"""One-sided paired signed-rank test: is a compressed setting's measure lower than the uncompressed one's?

Zero differences are dropped (or, as `pratt`, ranked and then dropped), ties get mean ranks. The statistic is made by
windows; the p-value is exact by counting for few differences without ties, else the normal approximation with
corrections for ties and continuity.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

CRITICAL = -1.6448536269514722  # fixed value: the lower 5 % point of the normal distribution


def statistic(pairs: DataFrame, keys: tuple[str, ...], zeros: str = "wilcox") -> DataFrame:
    """keys..., n, w_plus, ties (sum of t^3 - t) from pairs(keys..., base, other); differences are other - base."""
    d = pairs.withColumn("d", F.round(F.col("other") - F.col("base"), 9))
    if zeros == "wilcox":
        d = d.where("d != 0")
    groups = d.groupBy(*keys, F.abs("d").alias("size")).agg(F.count("*").alias("t"), F.count(F.when(F.col("d") > 0, 1)).alias("up"))
    before = F.coalesce(F.sum("t").over(Window.partitionBy(*keys).orderBy("size").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = groups.withColumn("mean_rank", before + (F.col("t") + 1) / 2.0).where("size > 0")
    found = ranked.groupBy(*keys).agg(F.sum("t").alias("n"), F.sum(F.col("mean_rank") * F.col("up")).alias("w_plus"), F.sum(F.col("t") * F.col("t") * F.col("t") - F.col("t")).alias("ties"))
    base = pairs.select(*keys).distinct()
    return base.join(found, list(keys), "left").select(*keys, *(F.coalesce(c, F.lit(0)).cast(t).alias(c) for c, t in (("n", "long"), ("w_plus", "double"), ("ties", "long"))))


def with_z(stat: DataFrame) -> DataFrame:
    """Adds z and star: significantly lower at 5 % by the normal approximation."""
    n = F.col("n").cast("double")
    variance = n * (n + 1) * (2 * n + 1) / 24 - F.col("ties") / 48
    z = F.when(variance > 0, (F.col("w_plus") - n * (n + 1) / 4 + 0.5) / F.sqrt(variance)).otherwise(0.0)
    return stat.withColumn("z", F.round(z, 9)).withColumn("star", F.col("z") < CRITICAL)


def exact_tail(n: int, w: float) -> float:
    """P(W+ <= w) for n untied differences, from the counts of subsets of 1..n by sum."""
    counts = np.zeros(n * (n + 1) // 2 + 1)
    counts[0] = 1
    for r in range(1, n + 1):
        counts[r:] = counts[r:] + counts[:-r].copy() if r else counts
    return float(counts[: int(math.floor(w)) + 1].sum() / 2.0**n)


def tail(n: int, w: float, ties: int) -> float:
    if n == 0:
        return 1.0
    if n <= 50 and ties == 0:
        return exact_tail(n, w)
    variance = n * (n + 1) * (2 * n + 1) / 24 - ties / 48
    if variance <= 0:
        return 1.0
    z = (w - n * (n + 1) / 4 + 0.5) / math.sqrt(variance)
    return 0.5 * math.erfc(-z / math.sqrt(2))


def wilcoxon_less(pairs: DataFrame, keys: tuple[str, ...], zeros: str = "wilcox") -> DataFrame:
    """keys..., n, w_plus, p."""
    stat = statistic(pairs, keys, zeros)

    def run(batches):
        for b in batches:
            p = [tail(n, w, t) for n, w, t in zip(*(b.column(c).to_pylist() for c in ("n", "w_plus", "ties")))]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in (*keys, "n", "w_plus")), pa.array(p, pa.float64())], names=[*keys, "n", "w_plus", "p"])

    kinds = dict(stat.dtypes)
    return stat.mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in (*keys, "n", "w_plus")) + ", p double")


def holm(p: list[float]) -> list[float]:
    """Adjusted p-values for several tests."""
    order, out, top = sorted(range(len(p)), key=lambda i: p[i]), [0.0] * len(p), 0.0
    for place, i in enumerate(order):
        top = max(top, min(1.0, (len(p) - place) * p[i]))
        out[i] = top
    return out


def with_holm(tests: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Adds p_holm: p adjusted for all tests with the same keys. Tests are few: one a setting."""
    place = Window.partitionBy(*keys).orderBy("p", *(c for c in tests.columns if c not in keys and c != "p"))
    step = F.least(F.lit(1.0), F.col("p") * (F.count("*").over(Window.partitionBy(*keys)) - F.row_number().over(place) + 1))
    return tests.withColumn("step", step).withColumn("p_holm", F.max("step").over(place)).drop("step")
