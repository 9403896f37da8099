"""Reports over metric records: retention, degradation, leaderboards, wrong-choice gaps, rank composition, advice."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def retention(values: DataFrame, keys: tuple[str, ...] = ("tier",), codec: str = "variant", base: str = "identity") -> DataFrame:
    """values with retention: percent of the uncompressed value at the same keys."""
    own = values.where(F.col(codec) == base).select(*keys, F.col("value").alias("base"))
    return values.join(own, list(keys)).withColumn("retention", F.round(F.when(F.col("base") > 0, F.col("value") / F.col("base") * 100).otherwise(0.0), 6)).drop("base")


def degradation(values: DataFrame, keys: tuple[str, ...] = ("variant",), tier: str = "tier") -> DataFrame:
    """values with drop (points lost since the smallest tier) and step (since the tier before)."""
    order = Window.partitionBy(*keys).orderBy(tier)
    first = F.first("value").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return values.withColumn("drop", F.round(first - F.col("value"), 6)).withColumn("step", F.round(F.coalesce(F.lag("value").over(order) - F.col("value"), F.lit(0.0)), 6))


def slope(values: DataFrame, sizes: dict[int, int], keys: tuple[str, ...] = ("variant",)) -> DataFrame:
    """keys..., slope: change of the value for each tenfold of the corpus size."""
    size = F.element_at(F.create_map(*(F.lit(x) for kv in sizes.items() for x in kv)), F.col("tier"))
    return values.withColumn("decade", F.log10(size.cast("double"))).groupBy(*keys).agg(F.round(F.regr_slope("value", "decade"), 6).alias("slope"))


def leaderboard(values: DataFrame, keys: tuple[str, ...], who: str) -> DataFrame:
    """values with place: 1 for the best in each column of keys; equal values share a place."""
    return values.withColumn("place", F.rank().over(Window.partitionBy(*keys).orderBy(F.desc("value"))))


def choice_gap(values: DataFrame, keys: tuple[str, ...], codec: str = "variant") -> DataFrame:
    """keys..., best, worst, gap: what a wrong codec costs at the same keys; ties go to the smaller name."""
    order = lambda sign: F.struct(sign * F.col("value"), F.col(codec))
    return values.groupBy(*keys).agg(F.min_by(codec, order(F.lit(-1))).alias("best"), F.min_by(codec, order(F.lit(1))).alias("worst"), F.round(F.max("value") - F.min("value"), 6).alias("gap"))


def codec_ranks(values: DataFrame, within: tuple[str, ...], codec: str = "variant") -> DataFrame:
    """codec, mean_rank, spread: a codec's rank in each dataset and how much it moves."""
    ranked = values.withColumn("place", F.rank().over(Window.partitionBy(*within).orderBy(F.desc("value"))))
    return ranked.groupBy(codec).agg(F.round(F.avg("place"), 6).alias("mean_rank"), F.round(F.stddev_pop("place"), 6).alias("spread"))


def rank_composition(run: DataFrame, roles: DataFrame, depth: int = 30, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys..., query_id, rank, role: which kind of item stands at each of the first ranks.

    roles(query_id, item_id, role) are those of a query; any other item is random.
    """
    return run.where(F.col("rank") <= depth).join(roles, ["query_id", "item_id"], "left").select(*keys, "query_id", "rank", F.coalesce("role", F.lit("random")).alias("role"))


def topk_stability(run: DataFrame, k: int = 10, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys..., query_id, tier, stable: share of the smallest tier's top k that is still there."""
    sets = run.where(F.col("rank") <= k).groupBy(*keys, "query_id", "tier").agg(F.collect_set("item_id").alias("items"))
    first = F.first("items").over(Window.partitionBy(*keys, "query_id").orderBy("tier").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return sets.select(*keys, "query_id", "tier", F.round(F.size(F.array_intersect("items", first)) / F.size(first), 9).alias("stable"))


def advise(values: DataFrame, stars: DataFrame, keys: tuple[str, ...] = ("ratio",), codec: str = "variant") -> DataFrame:
    """keys..., codec, value, star, advice on the largest tier: `use` the best of equal ratio, `avoid` what is significantly
    lower than uncompressed while the best of its ratio is not, else `possible`."""
    marked = values.join(stars.select(codec, "tier", "star"), [codec, "tier"], "left").withColumn("star", F.coalesce("star", F.lit(False)))
    last = marked.withColumn("last", F.max("tier").over(Window.partitionBy())).where("tier = last").drop("last")
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc("value"), codec))
    best_star = F.min_by("star", F.struct(-F.col("value"), F.col(codec))).over(Window.partitionBy(*keys))
    return last.withColumn("place", place).withColumn("best_star", best_star).select(
        *keys, codec, "value", "star", F.when(F.col("place") == 1, "use").when(F.col("star") & ~F.col("best_star"), "avoid").otherwise("possible").alias("advice"))
