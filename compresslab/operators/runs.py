"""Ranked lists of many systems: their worth, pruning of the worst, fusion by reciprocal ranks; a lexical run."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import tokens as T
from . import metrics
from .search import _Held

CONSTANT = 60


def effectiveness(runs: DataFrame, qrels: DataFrame, k: int = 10) -> DataFrame:
    """run_id, ndcg: mean NDCG@k of runs(run_id, query_id, item_id, rank)."""
    scored = metrics.evaluate(runs, qrels, (k,), ("run_id",)).where("metric = 'ndcg'")
    return scored.groupBy("run_id").agg(F.round(F.avg("value"), 12).alias("ndcg"))


def pruning(worth: DataFrame, drop: float = 0.2) -> DataFrame:
    """run_id, ndcg, kept: the floor(drop * runs) worst are not kept; ties go by run_id. Runs are few."""
    order = Window.orderBy("ndcg", F.desc("run_id"))
    return worth.withColumn("place", F.row_number().over(order)).withColumn("all", F.count("*").over(Window.partitionBy())).select("run_id", "ndcg", (F.col("place") > F.floor(F.col("all") * drop)).alias("kept"))


def prune(runs: DataFrame, qrels: DataFrame, drop: float = 0.2, k: int = 10) -> DataFrame:
    kept = pruning(effectiveness(runs, qrels, k), drop).where("kept").select("run_id")
    return runs.join(F.broadcast(kept), "run_id", "left_semi")


def fuse(runs: DataFrame, constant: int = CONSTANT, depth: int | None = None) -> DataFrame:
    """query_id, item_id, rrf, rank: items by the sum of 1 / (constant + rank) over the runs."""
    rows = runs if depth is None else runs.where(F.col("rank") <= depth)
    summed = rows.groupBy("query_id", "item_id").agg(F.round(F.sum(F.lit(1.0) / (F.lit(constant) + F.col("rank"))), 12).alias("rrf"))
    order = Window.partitionBy("query_id").orderBy(F.desc("rrf"), "item_id")
    return summed.withColumn("rank", F.row_number().over(order))


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != "")


def bm25_runs(queries: DataFrame, items: DataFrame, settings: dict[str, tuple[float, float]], k: int = 100) -> DataFrame:
    """run_id, query_id, item_id, rank, score of queries(query_id, text) over items(item_id, text); settings: run_id -> (k1, b).

    Queries are a stated set, whose words are sent. One scan counts the items that hold each word and their lengths; a second
    one scores every item that shares a word with a query under all settings, and a task keeps k a query, which are shuffled.
    """
    spark = queries.sparkSession
    rows = queries.select("query_id", "text").where("query_id is not null").collect()
    at, word = T.words(pa.array([r["text"] for r in rows], pa.string()))
    ids, place = np.unique(np.array([r["query_id"] for r in rows], dtype=np.int64), return_inverse=True)
    coded = word.dictionary_encode()
    vocabulary = coded.dictionary
    # the queries of a word stand together: asks[start[w] : start[w + 1]]
    pairs = np.unique(coded.indices.to_numpy(zero_copy_only=False).astype(np.int64) * max(1, len(ids)) + place[at])
    asks, start = pairs % max(1, len(ids)), np.searchsorted(pairs // max(1, len(ids)), np.arange(len(vocabulary) + 1))

    def held(column):
        """(row, word, count) of the query words in each text, and the words in each text."""
        row, token = T.words(column)
        w = pc.index_in(token, value_set=vocabulary)
        known = w.is_valid().to_numpy(zero_copy_only=False)
        key, n = np.unique(row[known] * max(1, len(vocabulary)) + w.drop_null().to_numpy(zero_copy_only=False), return_counts=True)
        return key // max(1, len(vocabulary)), key % max(1, len(vocabulary)), n, np.bincount(row, minlength=len(column))

    def count(batches):
        df, rows, texts, total = np.zeros(len(vocabulary), np.int64), 0, 0, 0
        for b in batches:
            for _, piece in T.pieces(b.column(0)):
                _, w, _, length = held(piece)
                df += np.bincount(w, minlength=len(df))
                rows, texts, total = rows + len(piece), texts + len(piece) - piece.null_count, total + int(length.sum())
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, [-1, -2, -3])), pa.array(np.append(df[at], [rows, texts, total]))], names=["word", "n"])

    totals = {r["word"]: r["n"] for r in items.select("text").mapInArrow(count, "word long, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()}
    df = np.array([totals.get(w, 0) for w in range(len(vocabulary))], dtype=np.float64)
    idf, mean = np.log(1 + (totals.get(-1, 0) - df + 0.5) / (df + 0.5)), totals.get(-3, 0) / max(1, totals.get(-2, 0))
    shared = spark.sparkContext.broadcast((idf, asks, start))
    ways = list(settings.items())

    def score(batches):
        idf, asks, start = shared.value
        best = [_Held(len(ids), k, np.finfo(float).tiny) for _ in ways]
        for b in batches:
            own = b.column(0).to_numpy(zero_copy_only=False)
            for first, piece in T.pieces(b.column(1)):
                row, w, tf, length = held(piece)
                n = start[w + 1] - start[w]
                entry = np.repeat(np.arange(len(w)), n)
                q = asks[np.arange(len(entry)) - np.repeat(np.cumsum(n) - n, n) + start[w][entry]]
                cell = q * len(piece) + row[entry]
                for (_, (k1, bb)), kept in zip(ways, best):
                    weight = idf[w] * tf * (k1 + 1) / (tf + k1 * (1 - bb + bb * length[row] / mean))
                    scored = np.round(np.bincount(cell, weight[entry], len(ids) * len(piece)), 9).reshape(len(ids), len(piece))
                    kept.add(scored, own[first : first + len(piece)])
        for i, kept in enumerate(best):
            if kept.rows:
                q, found, value = kept.cut()
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(q), i, np.int32)), pa.array(ids[q]), pa.array(found, pa.int64()), pa.array(value)], names=["way", "query_id", "item_id", "score"])

    scored = items.select(F.col("item_id").cast("long"), "text").mapInArrow(score, "way int, query_id long, item_id long, score double")
    order = Window.partitionBy("run_id", "query_id").orderBy(F.desc("score"), "item_id")
    named = scored.select(F.element_at(F.array(*(F.lit(r) for r, _ in ways)), F.col("way") + 1).alias("run_id"), "query_id", "item_id", "score")
    return named.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("run_id", "query_id", "item_id", "rank", "score")


def bm25(queries: DataFrame, items: DataFrame, k: int = 100, k1: float = 0.9, b: float = 0.4) -> DataFrame:
    """query_id, item_id, rank, score under one setting."""
    return bm25_runs(queries, items, {"": (k1, b)}, k).drop("run_id")
