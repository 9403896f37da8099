"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios.

Every text becomes the set of its character n-grams (runs of characters of a folded text, each word set off by one blank on
either side, so a run that starts with a blank is tied to a word's start), hashed to 2^BITS features. Feature j is binary
and scaled by r_j, the log of the ratio of its smoothed share among toxic and among clean training texts. A logistic
regression is fitted on the scaled features, with the mean loss plus l2 / (2 n) times the squared weights as its objective
(n training texts). At most `keep` features, those that tell most by the likelihood-ratio statistic, have a weight.

Null, empty and letterless texts have no features and get the score of the intercept. Repeated rows are scored alike, very
long ones whole. An empty training table gives a model that scores everything 0. Labels of one doc_id that disagree count as
toxic; rows with a null doc_id are never learned from, are scored, and held_out is null for them. Extra columns are never
read.
"""

from __future__ import annotations

import math
import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from . import words as W

ORDERS = (3, 4, 5, 6)
BITS = 20
PIECE = 128 << 10  # bytes of text at a time: a text's n-grams take some hundred bytes a byte meanwhile


def gram_ids(raw: np.ndarray, offsets: np.ndarray, wanted: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature) of every distinct n-gram of each text; wanted: only features where it is true."""
    seq, bounds = W.spaced(raw, offsets)
    # from the bytes of UTF-8 to characters; a text starts and ends with a blank, so none is cut
    starts = np.concatenate([[0], np.cumsum((seq & 0xC0) != 0x80)])
    seq, bounds = np.frombuffer(seq.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32), starts[bounds]
    row = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    out = []
    rolling = np.zeros(len(seq), dtype=np.uint64)
    value = seq.astype(np.uint64) + np.uint64(1)
    blank_inside = np.zeros(len(seq), dtype=bool)
    for i in range(max(ORDERS)):
        m = len(seq) - i
        if m <= 0:
            break
        rolling = rolling[:m] * np.uint64(0x100000001B3) + value[i:]
        if i >= 2:
            blank_inside = blank_inside[:m] | (seq[i - 1 : i - 1 + m] == 32)
        if i + 1 in ORDERS:
            feature = (rolling * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)
            ok = row[:m] == row[i:]
            ok &= ~blank_inside[:m]
            if wanted is not None:
                ok &= wanted[feature]
            at = np.flatnonzero(ok)
            out.append((row[at].astype(np.int64) << np.int64(BITS)) | feature[at].astype(np.int64))
    keys = np.unique(np.concatenate(out)) if out else np.zeros(0, np.int64)
    return keys >> np.int64(BITS), keys & np.int64((1 << BITS) - 1)


def _pieces(batch: pa.RecordBatch):
    for piece in C.small_batches(batch, "text", PIECE):
        yield piece, *C.text_bytes(piece.column("text"))


def _groups(first: np.ndarray, size: int, most: int = 1 << 18):
    """(first run, last run, first number, last number) of groups of whole runs, of about `most` numbers each; run i begins at first[i]."""
    cut = np.unique(np.searchsorted(first, np.arange(0, size, most)))
    for a, z in zip(cut, [*cut[1:], len(first)]):
        if a < z:
            yield a, z, first[a], first[z] if z < len(first) else size


def run_sums(value: np.ndarray, at: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of value[at] by runs, which begin at `first`; a group of runs at a time, so value[at] is never whole in memory."""
    out = np.empty(len(first))
    for a, z, low, high in _groups(first, len(at)):
        out[a:z] = np.add.reduceat(value[at[low:high]], first[a:z] - low)
    return out


def train(texts: pa.Array, labels: np.ndarray, keep: int = 20_000, l2: float = 2.0, steps: int = 400, alpha: float = 1.0) -> dict:
    """Fit the model on texts held in memory (a bounded sample). Deterministic."""
    labels = np.asarray(labels, dtype=np.float64)
    empty = {"index": np.zeros(0, np.int64), "weight": np.zeros(0, np.float32), "bias": -50.0}
    if len(labels) == 0 or labels.sum() == 0:
        return empty
    if labels.sum() == len(labels):
        return empty | {"bias": 50.0}
    batch = pa.RecordBatch.from_arrays([texts, pa.array(np.arange(len(labels)))], names=["text", "at"])
    counts = np.zeros((2, 1 << BITS), dtype=np.int32)
    for piece, raw, offsets in _pieces(batch):
        row, feature = gram_ids(raw, offsets)
        toxic = labels[piece.column("at").to_numpy()][row] > 0
        counts[1] += np.bincount(feature[toxic], minlength=1 << BITS).astype(np.int32)
        counts[0] += np.bincount(feature[~toxic], minlength=1 << BITS).astype(np.int32)
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    seen = np.flatnonzero(counts[0] + counts[1] >= 3)
    c0, c1 = counts[0][seen].astype(float), counts[1][seen].astype(float)
    del counts
    ratio = np.log((c1 + alpha) / (n1 + 2 * alpha)) - np.log((c0 + alpha) / (n0 + 2 * alpha))
    # the features kept are those that tell most, by the likelihood-ratio statistic
    expected1 = (c0 + c1) * n1 / (n1 + n0)
    expected0 = (c0 + c1) - expected1
    with np.errstate(divide="ignore", invalid="ignore"):
        gain = np.nan_to_num(c1 * np.log(c1 / expected1)) + np.nan_to_num(c0 * np.log(c0 / expected0))
    best = np.sort(np.argsort(-gain, kind="stable")[: min(keep, int((gain > 2.0).sum()))])
    index, scaled = seen[best], ratio[best]
    if len(index) == 0:
        return empty | {"bias": float(math.log(n1 / n0))}
    wanted = np.zeros(1 << BITS, dtype=bool)
    wanted[index] = True
    place = np.zeros(1 << BITS, dtype=np.int32)
    place[index] = np.arange(len(index))
    rows, cols = [], []
    for piece, raw, offsets in _pieces(batch):
        row, feature = gram_ids(raw, offsets, wanted)
        rows.append(piece.column("at").to_numpy()[row].astype(np.int32))
        cols.append(place[feature])
    # there are many more pairs of a text and a feature than texts or features: four bytes a number, none held twice
    rows = np.concatenate(rows)
    cols = np.concatenate(cols)
    del batch, texts, piece, raw, offsets, row, feature
    size = len(labels)
    # logistic regression on x = ratio * presence, by accelerated gradient steps with a bound on the curvature
    weight, bias = np.zeros(len(index)), float(math.log(n1 / n0))
    first_of = np.flatnonzero(np.diff(rows, prepend=np.int32(-1)))
    texts_with = rows[first_of]
    norm = np.sqrt(max(np.bincount(rows[low:high] - rows[low], weights=scaled[cols[low:high]] ** 2).max() for _, _, low, high in _groups(first_of, len(rows))) + 1.0)
    unit = scaled / norm
    ahead, ahead_bias, t = weight.copy(), bias, 1.0
    rate = 4.0
    # x is divided by `norm`, so weights are larger by it and their penalty smaller by its square
    penalty = l2 / size / norm**2
    # sums go over runs: rows come sorted by text, and once more by feature
    order = np.argsort(cols, kind="stable")
    by_feature, first_by = rows[order], np.concatenate([[0], np.cumsum(np.bincount(cols, minlength=len(index)))[:-1]])
    del order, rows
    for _ in range(steps):
        z = np.zeros(size)
        z[texts_with] = run_sums(unit * ahead, cols, first_of)
        err = 1 / (1 + np.exp(-np.clip(z + ahead_bias, -40, 40))) - labels
        grad = unit * run_sums(err, by_feature, first_by) / size + penalty * ahead
        new_weight, new_bias = ahead - rate * size / max(n1, 1) * grad, ahead_bias - rate * err.mean()
        t2 = (1 + math.sqrt(1 + 4 * t * t)) / 2
        ahead, ahead_bias = new_weight + (t - 1) / t2 * (new_weight - weight), new_bias + (t - 1) / t2 * (new_bias - bias)
        weight, bias, t = new_weight, new_bias, t2
    return {"index": index, "weight": (unit * weight).astype(np.float64), "bias": float(bias)}


def score_texts(column: pa.Array, model: dict) -> np.ndarray:
    """Scores in [0, 1] of whole texts."""
    table = np.zeros(1 << BITS, dtype=np.float32)
    table[model["index"]] = model["weight"]
    wanted = table != 0
    batch = pa.RecordBatch.from_arrays([column], names=["text"])
    out = []
    for piece, raw, offsets in _pieces(batch):
        row, feature = gram_ids(raw, offsets, wanted)
        z = np.bincount(row, weights=table[feature], minlength=piece.num_rows) + model["bias"]
        out.append(1 / (1 + np.exp(-np.clip(z, -500, 500))))
    return np.concatenate(out) if out else np.zeros(0)


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, positives: int = 3000, negatives: int = 5000) -> dict:
    """Train on a bounded sample: about `positives` toxic and `negatives` clean labelled rows, chosen by a hash of doc_id.

    Only rows whose crc32(doc_id as text) mod 5 is not 0 are learned from. The sample, which these two
    parameters bound, is fitted inside one task; the driver receives the weights alone.
    """
    marked = (
        labels.select("doc_id", "toxic").where("doc_id is not null and toxic is not null")
        .where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
        .groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    )
    chosen = C.bounded_per_class(marked, "toxic", "doc_id", {0: negatives, 1: positives})
    sample = docs.select("doc_id", "text").where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0).join(F.broadcast(chosen), "doc_id").select("text", F.col("toxic").cast("int").alias("toxic"), F.xxhash64("doc_id", "text").alias("at"))

    def run(batches):
        texts, marks, order = [], [], []
        for b in batches:
            texts.append(b.column("text").cast(pa.large_string()))
            marks.append(b.column("toxic").to_numpy(zero_copy_only=False))
            order.append(b.column("at").to_numpy(zero_copy_only=False))
        if texts:
            by = np.argsort(np.concatenate(order), kind="stable")
            whole = pa.concat_arrays(texts)
            texts.clear()
            whole = [whole.take(pa.array(by))]
            model = train(whole.pop(), np.concatenate(marks)[by])
        else:
            model = train(pa.array([], pa.large_string()), np.zeros(0))
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], names=["model"])

    rows = C.materialize(sample, "toxic-sample").coalesce(1).mapInArrow(run, C.schema(model=C.BINARY)).collect()
    return pickle.loads(rows[0][0]) if rows else train(pa.array([], pa.large_string()), np.zeros(0))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score of every row of docs; one narrow pass."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(score_texts(b.column("text"), shared.value), pa.float64())], names=["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, C.schema(doc_id=C.LONG, score=C.DOUBLE))


def drop_toxic(docs: DataFrame, model: dict, threshold: float = 0.5) -> DataFrame:
    """docs without the rows that score `threshold` or more; all columns stay as they are."""
    import pyarrow.compute as pc

    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.mapInArrow(C.keep_rows(lambda b: pc.less(pa.array(score_texts(b.column("text"), shared.value)), threshold)), docs.schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "labels")
    scored = score(docs, fit(spark, docs, labels))
    return scored.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
