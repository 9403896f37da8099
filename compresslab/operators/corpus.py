"""Corpora of growing size around fixed queries: planted queries, passages, distractors, filler, nested tiers.

A tier holds the relevant items, the mined distractors and as much filler as its size asks for; tiers are
nested, so an item is stored once with the smallest tier that holds it. Filler comes in the order of a hash, ranked
without a global sort: counts of hash buckets give every bucket its offset, and only rows inside a bucket are ordered.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T

RELEVANT = 10
PASSAGE = 286
WEIGHTS = (3.0, 2.5, 2.0, 1.6, 1.3, 1.0, 0.8, 0.6, 0.5, 0.4)


def planted_parameters(vectors: DataFrame) -> tuple[int, int, int]:
    """(vectors, groups, queries): groups of ten vectors, and how many of these become queries."""
    n = vectors.count()
    return n, n // RELEVANT, min(20, n // 50)


def planted_queries(vectors: DataFrame, weighted: bool = False) -> DataFrame:
    """query_id, vec: sums of the vectors of a group (vec_id modulo the number of groups), weighted or not.

    Where the number of vectors is no multiple of ten, the first groups have an eleventh member: it counts without weights,
    and is relevant either way.
    """
    n, m, q = planted_parameters(vectors)
    rows = vectors.where(F.col("vec_id") % m < q).select((F.col("vec_id") % m).alias("query_id"), (F.col("vec_id") / m).cast("int").alias("i"), F.posexplode("embedding").alias("pos", "v"))
    weight = F.get(F.array(*(F.lit(w) for w in WEIGHTS)), F.col("i")) if weighted else F.lit(1.0)  # an eleventh member has no weight
    sums = rows.groupBy("query_id", "pos").agg(F.round(F.sum(F.col("v").cast("double") * weight), 12).alias("v"))
    return sums.groupBy("query_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("vec"))


def planted_qrels(vectors: DataFrame, graded: bool = False) -> DataFrame:
    """query_id, item_id, grade of the group's members."""
    n, m, q = planted_parameters(vectors)
    i = (F.col("vec_id") / m).cast("int")
    grade = F.when(i < 2, 3).when(i < 5, 2).otherwise(1) if graded else F.lit(1)
    return vectors.where(F.col("vec_id") % m < q).select((F.col("vec_id") % m).alias("query_id"), F.col("vec_id").alias("item_id"), grade.alias("grade"))


def passages(docs: DataFrame, width: int = PASSAGE) -> DataFrame:
    """doc_id, i, text: slices of `width` characters, each text cut in one pass."""

    def run(batches):
        for b in batches:
            for at, piece in T.pieces(b.column(1), size=1 << 22):
                texts = piece.to_pylist()
                n = np.array([-(-len(t or "") // width) for t in texts], dtype=np.int64)
                ids = b.column(0).slice(at, len(piece)).take(pa.array(np.repeat(np.arange(len(piece)), n)))
                i = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                yield pa.RecordBatch.from_arrays([ids, pa.array(i.astype(np.int32)), pa.array([t[j : j + width] for t in texts if t for j in range(0, len(t), width)], pa.string())], names=["doc_id", "i", "text"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, i int, text string")


def containment(items: DataFrame, queries: DataFrame) -> DataFrame:
    """query_id, item_id, grade: items whose text contains a query's text. Queries are a stated small set.

    A text is looked through once for the first eight bytes of all queries; where these stand, the whole query is compared.
    """
    asked = [(r["query_id"], r["text"].encode()) for r in queries.select("query_id", "text").where("text is not null").collect()]
    short = [(i, t) for i, t in asked if len(t) < 8]
    by_key: dict[int, list] = {}
    for i, t in asked:
        if len(t) >= 8:
            by_key.setdefault(int.from_bytes(t[:8], "little"), []).append((i, t))
    keys = np.array(sorted(by_key), dtype=np.uint64)
    factor = np.uint64(0x9E3779B97F4A7C15)

    def run(batches):
        mark = np.zeros(1 << 16, bool)
        mark[(keys * factor) >> np.uint64(48)] = True
        for b in batches:
            for first, piece in T.pieces(b.column(1)):
                texts = [(t or "").encode() for t in piece.to_pylist()]
                end = np.cumsum([len(t) for t in texts])
                data = b"".join(texts)
                found = {(i, row) for row, t in enumerate(texts) for i, q in short if q in t and piece[row].is_valid}
                for o in range(8) if len(keys) else ():
                    window = np.frombuffer(data, np.uint64, max(0, (len(data) - o) // 8), o) if len(data) - o >= 8 else np.zeros(0, np.uint64)
                    hit = np.flatnonzero(mark[(window * factor) >> np.uint64(48)])
                    hit = hit[keys[np.minimum(np.searchsorted(keys, window[hit]), len(keys) - 1)] == window[hit]]
                    for at, key in zip((hit * 8 + o).tolist(), window[hit].tolist()):
                        row = int(np.searchsorted(end, at, side="right"))
                        found.update((i, row) for i, q in by_key[key] if at + len(q) <= end[row] and data[at : at + len(q)] == q)
                pairs = sorted(found)
                ids = b.column(0).slice(first, len(piece)).take(pa.array([r for _, r in pairs], pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in pairs], pa.int64()), ids, pa.array(np.ones(len(pairs), np.int32))], names=["query_id", "item_id", "grade"])

    return items.select(F.col("item_id").cast("long"), "text").mapInArrow(run, "query_id long, item_id long, grade int")


def overlapping_passages(rel: DataFrame, docs: DataFrame, queries: DataFrame, width: int = PASSAGE) -> DataFrame:
    """query_id, doc_id, i, grade: the passages in which a query's text stands in a document that contains it, its first place there."""
    at = rel.select("query_id", F.col("item_id").alias("doc_id")).join(F.broadcast(queries.withColumnRenamed("text", "q")), "query_id").join(docs, "doc_id")
    place = F.expr("instr(text, q)") - 1
    spans = at.where(F.length("q") > 0).select("query_id", "doc_id", F.explode(F.sequence((place / width).cast("int"), ((place + F.length("q") - 1) / width).cast("int"))).alias("i"))
    return spans.select("query_id", "doc_id", "i", F.lit(1).alias("grade"))


def select_qrels(qrels: DataFrame, n_rel: int = RELEVANT) -> DataFrame:
    """Queries with n_rel relevant items at least, cut to exactly n_rel: best grades first, then smaller ids."""
    order = Window.partitionBy("query_id").orderBy(F.desc("grade"), "item_id")
    return (
        qrels.where("grade > 0").withColumn("place", F.row_number().over(order)).withColumn("all", F.count("*").over(Window.partitionBy("query_id")))
        .where((F.col("all") >= n_rel) & (F.col("place") <= n_rel)).select("query_id", "item_id", "grade")
    )


def distractors(fused: DataFrame, qrels: DataFrame, per_query: int = 100) -> DataFrame:
    """query_id, item_id, rank: the best of fused(query_id, item_id, rank) that are not relevant to the query."""
    rest = fused.join(F.broadcast(qrels.where("grade > 0").select("query_id", "item_id")), ["query_id", "item_id"], "left_anti")
    order = Window.partitionBy("query_id").orderBy("rank", "item_id")
    return rest.withColumn("place", F.row_number().over(order)).where(F.col("place") <= per_query).select("query_id", "item_id", F.col("place").alias("rank"))


def core(qrels: DataFrame, mined: DataFrame) -> DataFrame:
    """item_id, role of the protected items: relevant wins over distractor."""
    return qrels.select("item_id", F.lit("relevant").alias("role")).unionByName(mined.select("item_id", F.lit("distractor").alias("role"))).groupBy("item_id").agg(F.max("role").alias("role"))


def hash_rank(items: DataFrame, key: Column) -> DataFrame:
    """items with place (from 1): the rank of a hex digest over all rows, by bucket offsets and ranks inside buckets."""
    keyed = items.withColumn("key", key).withColumn("bucket", F.substring("key", 1, 4))
    counts = keyed.groupBy("bucket").count()  # 65536 rows at most
    offsets = counts.withColumn("offset", F.sum("count").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))).select("bucket", F.coalesce("offset", F.lit(0)).alias("offset"))
    inside = F.row_number().over(Window.partitionBy("bucket").orderBy("key", "item_id"))
    return keyed.withColumn("inside", inside).join(F.broadcast(offsets), "bucket").withColumn("place", F.col("offset") + F.col("inside")).drop("key", "bucket", "inside", "offset")


def ladder(items: DataFrame, protected: DataFrame, sizes: list[int], seed: str = "", strict: bool = True) -> DataFrame:
    """item_id, role, tier (from 1) of the items within the largest size; protected(item_id, role) are in all tiers.

    Not strict: protected items may outnumber the smallest tiers, which then hold them all and no filler.
    """
    n = protected.count()
    if strict and n > sizes[0]:
        raise ValueError(f"the smallest tier must hold the {n} protected items")
    rest = items.select("item_id").join(F.broadcast(protected.select("item_id")), "item_id", "left_anti")
    placed = hash_rank(rest, F.md5(F.concat(F.lit(seed), F.col("item_id").cast("string"))))
    tier = F.lit(None).cast("int")
    for t in range(len(sizes), 0, -1):
        tier = F.when(F.col("place") <= sizes[t - 1] - n, t).otherwise(tier)
    filler = placed.select("item_id", F.lit("random").alias("role"), tier.alias("tier")).where("tier is not null")
    return protected.select("item_id", "role", F.lit(1).alias("tier")).unionByName(filler)


def random_subset(items: DataFrame, qrels: DataFrame, sizes: list[int], seed: str = "") -> DataFrame:
    """The naive contrast: relevant items and filler alone, without protected distractors."""
    return ladder(items, qrels.select("item_id", F.lit("relevant").alias("role")).distinct(), sizes, seed)


def audit(tiers: DataFrame, qrels: DataFrame, mined: DataFrame, sizes: list[int], n_rel: int, per_query: int) -> DataFrame:
    """check, tier, expected, actual."""
    queries = qrels.select("query_id").distinct().count()
    spark = tiers.sparkSession
    size = tiers.groupBy("tier").count().select("tier", F.sum("count").over(Window.orderBy("tier")).alias("actual"))
    wanted = spark.createDataFrame([(t + 1, n) for t, n in enumerate(sizes)], "tier int, expected long")
    checks = wanted.join(size, "tier").select(F.lit("size").alias("check"), "tier", "expected", "actual")
    per = lambda df, name, want: df.groupBy("query_id").count().agg(F.count(F.when(F.col("count") == want, 1)).alias("actual")).select(F.lit(name).alias("check"), F.lit(0).alias("tier"), F.lit(queries).cast("long").alias("expected"), "actual")
    twice = tiers.groupBy("item_id").count().where("count > 1").agg(F.count("*").alias("actual")).select(F.lit("items_in_two_roles").alias("check"), F.lit(0).alias("tier"), F.lit(0).cast("long").alias("expected"), "actual")
    return checks.unionByName(per(qrels, "relevant_per_query", n_rel)).unionByName(per(mined, "distractors_per_query", per_query)).unionByName(twice)
