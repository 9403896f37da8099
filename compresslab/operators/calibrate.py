"""Statistics that codecs learn: per-dimension quantiles in several scopes, covariance, hash samples.

Scopes: one set for each batch, one from a hash sample, one exact over everything, one from mergeable
sketches over everything (the one that scales). Thresholds are rounded to 12 digits so that engines agree.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V

DIGITS = 12
CLIP = (0.025, 0.975)
LEVELS = tuple(sorted({*CLIP, *(i / 256 for i in range(1, 256))}))


@dataclass
class Calibration:
    """Per-dimension statistics as arrays over positions; what is not needed stays None."""

    quantiles: dict[float, np.ndarray] = field(default_factory=dict)
    low: np.ndarray | None = None
    high: np.ndarray | None = None
    mean: np.ndarray | None = None
    basis: np.ndarray | None = None
    codebook: np.ndarray | None = None

    def at(self, level: float) -> np.ndarray:
        return self.quantiles[level]

    def first(self, dims: int) -> Calibration:
        """The statistics of the first dimensions, for codecs that follow a truncation."""
        cut = lambda a: None if a is None else a[:dims]
        return Calibration({k: v[:dims] for k, v in self.quantiles.items()}, cut(self.low), cut(self.high), cut(self.mean))


def hash_sample(df: DataFrame, id_col: str, fraction: float, seed: int = 0) -> DataFrame:
    """A sample that depends on ids only, not on partitions."""
    return df.where(F.pmod(F.xxhash64(F.col(id_col), F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))


def quantile_rows(df: DataFrame, levels, keys: tuple[str, ...] = (), id_col: str = "vec_id", vec_col: str = "embedding", method: str = "exact") -> DataFrame:
    """keys..., pos, q (array in the order of levels), low, high: one row for each key and dimension."""
    rows = df.select(*keys, F.posexplode(vec_col).alias("pos", "v")).select(*keys, "pos", F.col("v").cast("double").alias("v"))
    levels = list(levels)
    wanted = F.array(*(F.lit(float(x)) for x in levels))
    if method == "exact":
        q = F.percentile("v", wanted)
    elif method == "kll":
        q = F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("v", F.lit(400)), wanted)
    elif method == "approx":
        q = F.percentile_approx("v", levels, 10_000)
    else:
        raise ValueError(method)
    return rows.groupBy(*keys, "pos").agg(F.transform(q, lambda x: F.round(x, DIGITS)).alias("q"), F.min("v").alias("low"), F.max("v").alias("high"))


def quantiles(df: DataFrame, levels=LEVELS, vec_col: str = "embedding", method: str = "exact") -> Calibration:
    """Collect the statistics of one set of vectors: dims x levels numbers, however many vectors there are."""
    rows = sorted(quantile_rows(df, levels, vec_col=vec_col, method=method).collect(), key=lambda r: r["pos"])
    q = np.array([r["q"] for r in rows]).reshape(len(rows), -1)
    return Calibration({level: q[:, i] for i, level in enumerate(levels)}, np.array([r["low"] for r in rows]), np.array([r["high"] for r in rows]))


def batch_quantiles(df: DataFrame, batch_col: str, levels, vec_col: str = "embedding", method: str = "exact") -> dict[int, Calibration]:
    """A calibration for each batch."""
    out: dict[int, list] = {}
    for r in quantile_rows(df, levels, (batch_col,), vec_col=vec_col, method=method).collect():
        out.setdefault(r[batch_col], []).append(r)
    found = {}
    for batch, rows in out.items():
        rows.sort(key=lambda r: r["pos"])
        q = np.array([r["q"] for r in rows])
        found[batch] = Calibration({level: q[:, i] for i, level in enumerate(levels)}, np.array([r["low"] for r in rows]), np.array([r["high"] for r in rows]))
    return found


def counted_quantiles(df: DataFrame, levels, read, ways: list, vec_col: str) -> list[Calibration]:
    """Exact quantiles of ways[i](values, positions), each in one calibration, from one scan.

    read makes a matrix of the Arrow column vec_col. A task sends distinct values with their counts, which are few where
    values are counts.
    """
    levels = list(levels)

    def run(batches):
        for b in batches:
            for start in range(0, b.num_rows, 2048):
                x = np.sort(np.ascontiguousarray(read(b.column(0).slice(start, 2048)).T), axis=1)
                first = np.ones(x.shape, bool)
                first[:, 1:] = x[:, 1:] != x[:, :-1]
                flat = np.flatnonzero(first)
                pos, v, n = flat // x.shape[1], x.ravel()[flat], np.diff(np.append(flat, x.size))
                for w, way in enumerate(ways):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pos), w, np.int32)), pa.array(pos.astype(np.int32)), pa.array(way(v, pos)), pa.array(n)], names=["way", "pos", "v", "n"])

    rows = df.select(vec_col).mapInArrow(run, "way int, pos int, v double, n long")
    q = F.percentile("v", F.array(*(F.lit(float(x)) for x in levels)), F.col("n"))
    found = rows.groupBy("way", "pos").agg(F.transform(q, lambda x: F.round(x, DIGITS)).alias("q"), F.min("v").alias("low"), F.max("v").alias("high")).collect()
    out = []
    for w in range(len(ways)):
        own = sorted((r for r in found if r["way"] == w), key=lambda r: r["pos"])
        q = np.array([r["q"] for r in own]).reshape(len(own), -1)
        out.append(Calibration({level: q[:, i] for i, level in enumerate(levels)}, np.array([r["low"] for r in own]), np.array([r["high"] for r in own])))
    return out


def counted_batch_quantiles(df: DataFrame, batch_col: str, levels, ways: list, vec_col: str) -> list[dict[int, Calibration]]:
    """Exact quantiles of ways[i](values, positions) in each batch, from one scan of vectors that hold counts.

    A task sends the distinct counts of a dimension with their numbers, which are few; ways keep the order of counts.
    """
    levels = list(levels)

    def run(batches):
        for b in batches:
            own = b.column(0).to_numpy(zero_copy_only=False)
            for batch in np.unique(own):
                x = np.sort(np.ascontiguousarray(V.matrix(b.column(1).filter(pa.array(own == batch))).T), axis=1)
                first = np.ones(x.shape, bool)
                first[:, 1:] = x[:, 1:] != x[:, :-1]
                flat = np.flatnonzero(first)
                pos, v, n = flat // x.shape[1], x.ravel()[flat], np.diff(np.append(flat, x.size))
                for w, way in enumerate(ways):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pos), w, np.int32)), pa.array(np.full(len(pos), batch, np.int32)), pa.array(pos.astype(np.int32)), pa.array(way(v, pos)), pa.array(n)], names=["way", "batch", "pos", "v", "n"])

    rows = df.where(F.col(batch_col).isNotNull()).select(F.col(batch_col).cast("int"), vec_col).mapInArrow(run, "way int, batch int, pos int, v double, n long")
    q = F.percentile("v", F.array(*(F.lit(float(x)) for x in levels)), F.col("n"))
    held: dict[tuple[int, int], list] = {}
    for r in rows.groupBy("way", "batch", "pos").agg(F.transform(q, lambda x: F.round(x, DIGITS)).alias("q"), F.min("v").alias("low"), F.max("v").alias("high")).collect():
        held.setdefault((r["way"], r["batch"]), []).append(r)
    out: list[dict[int, Calibration]] = [{} for _ in ways]
    for (w, batch), own in held.items():
        own.sort(key=lambda r: r["pos"])
        q = np.array([r["q"] for r in own]).reshape(len(own), -1)
        out[w][batch] = Calibration({level: q[:, i] for i, level in enumerate(levels)}, np.array([r["low"] for r in own]), np.array([r["high"] for r in own]))
    return out


def moments(df: DataFrame, vec_col: str = "embedding", read=V.matrix) -> DataFrame:
    """i, j, s_ij, s_i, s_j, n summed over all vectors: the Gram pass. A task sends one dims x dims matrix."""

    def run(batches):
        n, total, gram = 0, None, None
        for b in batches:
            if not b.num_rows:
                continue
            x = read(b.column(0))
            if total is None:
                total, gram = np.zeros(x.shape[1]), np.zeros((x.shape[1], x.shape[1]))
            n, total, gram = n + len(x), total + x.sum(axis=0), gram + x.T @ x
        if n:
            d = len(total)
            i, j = np.divmod(np.arange(d * d), d)
            yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(gram.ravel()), pa.array(total[i]), pa.array(total[j]), pa.array(np.full(d * d, n))], names=["i", "j", "sij", "si", "sj", "n"])

    part = df.select(vec_col).mapInArrow(run, "i int, j int, sij double, si double, sj double, n long")
    return part.groupBy("i", "j").agg(*(F.sum(c).alias(c) for c in ("sij", "si", "sj", "n")))


def covariance(df: DataFrame, vec_col: str = "embedding") -> DataFrame:
    """i, j, cov: sample covariance of every pair of dimensions."""
    return moments(df, vec_col).select("i", "j", ((F.col("sij") - F.col("si") * F.col("sj") / F.col("n")) / (F.col("n") - 1)).alias("cov"))


def principal(df: DataFrame, vec_col: str = "embedding", read=V.matrix) -> Calibration:
    """Mean and all principal directions, largest variance first; a direction's largest loading is positive."""
    rows = moments(df, vec_col, read).collect()  # dims squared numbers
    d = 1 + max(r["i"] for r in rows)
    gram, total, n = np.zeros((d, d)), np.zeros(d), rows[0]["n"]
    for r in rows:
        gram[r["i"], r["j"]] = r["sij"]
        total[r["i"]] = r["si"]
    mean = total / n
    value, vector = np.linalg.eigh((gram - np.outer(total, total) / n) / max(1, n - 1))
    basis = vector[:, np.argsort(-value, kind="stable")].T
    at = np.abs(basis).argmax(axis=1)
    basis *= np.sign(basis[np.arange(d), at])[:, None]
    out = Calibration(mean=mean, basis=basis)
    out.variance = np.sort(value)[::-1]
    return out
