"""Vector codecs: what each keeps of a vector, how it is scored, and what it costs in bits.

A codec turns a matrix of native vectors into a matrix of codes, and codes into the matrix whose
cosines rank the items (`space`). Learned numbers come as a Calibration. Codecs are plain values, so a
list of them travels to the executors and is applied to each Arrow batch in one scan.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rounding as R
from ..functions import vectors as V
from .calibrate import CLIP, Calibration


@dataclass(frozen=True)
class Codec:
    """Uncompressed vectors, and the base of all codecs."""

    name: str = "identity"

    def levels(self) -> tuple[float, ...]:
        """Quantile levels that the codec learns from."""
        return ()

    def encode(self, x: np.ndarray, c: Calibration) -> np.ndarray:
        return x

    def space(self, code: np.ndarray, c: Calibration) -> np.ndarray:
        """The vectors that are compared by cosine."""
        return code

    def decode(self, code: np.ndarray, c: Calibration) -> np.ndarray:
        """The nearest native vectors that the codes stand for."""
        return self.space(code, c)

    def bits(self, dims: int, native: int = 32) -> int:
        return dims * native

    def ratio(self, dims: int, native: int = 32) -> float:
        return dims * native / self.bits(dims, native)


def identity() -> Codec:
    return Codec()


@dataclass(frozen=True)
class FloatCast(Codec):
    form: str = "fp16"
    saturate: bool = False

    def encode(self, x, c):
        return R.round_array(x, self.form, self.saturate)

    def bits(self, dims, native=32):
        return dims * min(native, R.FORMATS[self.form].bits)  # a cast to the native width or wider keeps everything


def float_cast(form: str, saturate: bool = False) -> Codec:
    return FloatCast(form, form, saturate)


@dataclass(frozen=True)
class Bins(Codec):
    """Unsigned bin numbers: equal widths between two quantiles (or the extremes), or equal counts."""

    width: int = 8
    equal_width: bool = True
    clip: tuple[float, float] | None = CLIP
    scoring: str = "raw"

    def levels(self):
        return (self.clip or ()) if self.equal_width else tuple(i / 2**self.width for i in range(1, 2**self.width))

    def _range(self, c):
        return (c.low, c.high) if self.clip is None else (c.at(self.clip[0]), c.at(self.clip[1]))

    def edges(self, c: Calibration) -> np.ndarray:
        return np.stack([c.at(level) for level in self.levels()], axis=1)

    def encode(self, x, c):
        top = 2**self.width - 1
        if self.equal_width:
            low, high = self._range(c)
            span = high - low
            with np.errstate(divide="ignore", invalid="ignore"):
                code = np.floor((np.clip(x, low, high) - low) / span * (top + 1))
            return np.clip(np.where(span > 0, code, 0), 0, top)
        edges = self.edges(c)
        return np.stack([np.searchsorted(edges[j], x[:, j], side="right") for j in range(x.shape[1])], axis=1).astype(np.float64)

    def space(self, code, c):
        if self.scoring == "raw":
            return code
        if self.scoring == "centred":
            return code - (2**self.width - 1) / 2
        return self.decode(code, c)

    def decode(self, code, c):
        if self.equal_width:
            low, high = self._range(c)
            return low + (code + 0.5) * (high - low) / 2**self.width
        edges = self.edges(c)
        low = np.concatenate([c.low[:, None] if c.low is not None else edges[:, :1], edges], axis=1)
        high = np.concatenate([edges, c.high[:, None] if c.high is not None else edges[:, -1:]], axis=1)
        middle = (low + high) / 2
        return middle[np.arange(code.shape[1])[None, :], code.astype(np.int64)]

    def bits(self, dims, native=32):
        return dims * self.width


def equal_width(bits: int, clip: tuple[float, float] | None = CLIP, scoring: str = "raw") -> Codec:
    name = f"equal_width_{bits}" + ("" if clip else "_noclip") + ("" if scoring == "raw" else f"_{scoring}")
    return Bins(name, bits, True, clip, scoring)


def percentile_bins(bits: int, scoring: str = "raw") -> Codec:
    return Bins(f"percentile_{bits}" + ("" if scoring == "raw" else f"_{scoring}"), bits, False, None, scoring)


@dataclass(frozen=True)
class Binary(Codec):
    """One bit a dimension: above zero, or above the dimension's median."""

    threshold: str = "zero"
    scoring: str = "signed"

    def levels(self):
        return (0.5,) if self.threshold == "median" else ()

    def encode(self, x, c):
        return (x > (0.0 if self.threshold == "zero" else c.at(0.5))).astype(np.float64)

    def space(self, code, c):
        return code if self.scoring == "raw" else 2 * code - 1

    def bits(self, dims, native=32):
        return dims


def binary(threshold: str = "zero", scoring: str = "signed") -> Codec:
    return Binary(f"bits_{threshold}" + ("" if scoring == "signed" else "_raw"), threshold, scoring)


@dataclass(frozen=True)
class Truncate(Codec):
    """The first `keep` dimensions, then any other codec on these."""

    keep: int = 32
    then: Codec = Codec()
    renormalize: bool = False

    def levels(self):
        return self.then.levels()

    def encode(self, x, c):
        x = x[:, : self.keep]
        if self.renormalize:
            size = np.linalg.norm(x, axis=1, keepdims=True)
            x = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
        return self.then.encode(x, c.first(self.keep))

    def space(self, code, c):
        return self.then.space(code, c.first(self.keep))

    def decode(self, code, c):
        kept = self.then.decode(code, c.first(self.keep))
        return np.concatenate([kept, np.zeros((len(kept), max(0, self._dims(c) - kept.shape[1])))], axis=1)

    def _dims(self, c: Calibration) -> int:
        return len(c.low) if c.low is not None else len(next(iter(c.quantiles.values()), np.zeros(self.keep)))

    def bits(self, dims, native=32):
        return self.then.bits(min(self.keep, dims), native)


def truncate(keep: int, renormalize: bool = False) -> Codec:
    return Truncate(f"truncate_{keep}", keep, Codec(), renormalize)


def compose(first: Truncate, second: Codec) -> Codec:
    """Truncation followed by another codec, which learns from the kept dimensions only."""
    return Truncate(f"{first.name}+{second.name}", first.keep, second, first.renormalize)


@dataclass(frozen=True)
class Pca(Codec):
    keep: int = 32
    center: bool = True
    whiten: bool = False

    def encode(self, x, c):
        code = (x - c.mean if self.center else x) @ c.basis[: self.keep].T
        return code / np.sqrt(np.maximum(c.variance[: self.keep], 1e-30)) if self.whiten else code

    def decode(self, code, c):
        if self.whiten:
            code = code * np.sqrt(np.maximum(c.variance[: self.keep], 1e-30))
        return code @ c.basis[: self.keep] + (c.mean if self.center else 0)

    def bits(self, dims, native=32):
        return min(self.keep, dims) * native


def pca(keep: int, center: bool = True, whiten: bool = False) -> Codec:
    return Pca(f"pca_{keep}", keep, center, whiten)


def hash_signs(nbits: int, dims: int) -> np.ndarray:
    """A +1/-1 matrix from digests of "bit:dimension", which SQL engines can rebuild."""
    return np.array([[1.0 if int(hashlib.md5(f"{b}:{p}".encode()).hexdigest()[:2], 16) < 128 else -1.0 for p in range(dims)] for b in range(nbits)])


@dataclass(frozen=True)
class Lsh(Codec):
    """Signs of random projections. Gaussian directions, orthonormal where no more than dimensions; or hashed +1/-1."""

    nbits: int = 64
    seed: int = 1
    rotate: bool = True
    hashed: bool = False
    thresholds: str = "zero"

    def frame(self, dims: int) -> np.ndarray:
        if self.hashed:
            return hash_signs(self.nbits, dims)
        g = np.random.Generator(np.random.Philox(self.seed)).standard_normal((max(self.nbits, 1), dims))
        if self.rotate and self.nbits <= dims:
            q, r = np.linalg.qr(g.T)
            g = (q * np.sign(np.diag(r))).T
        return g

    def encode(self, x, c):
        projected = x @ _frame(self, x.shape[1]).T
        if self.thresholds == "median":  # medians of the projections stand in the calibration's codebook
            return (projected > c.codebook).astype(np.float64)
        return (projected > 0).astype(np.float64)

    def space(self, code, c):
        return 2 * code - 1

    def bits(self, dims, native=32):
        return self.nbits


def family(codec: Codec, dims: int):
    """The same for codecs whose codes are prefixes of each other's, as their directions are drawn one after the other; else None."""
    alone = not isinstance(codec, Lsh) or codec.thresholds != "zero" or (codec.rotate and not codec.hashed and codec.nbits <= dims)
    return None if alone else (codec.hashed, None if codec.hashed else codec.seed)


def signed(codec: Codec) -> bool:
    """Whether the compared vectors hold +1 and -1 only."""
    inner = codec.then if isinstance(codec, Truncate) else codec
    return isinstance(inner, Lsh) or (isinstance(inner, Binary) and inner.scoring != "raw")


_frames: dict = {}


def _frame(codec: Lsh, dims: int) -> np.ndarray:
    """Made once a process from the seed, never shipped."""
    key = (codec, dims)
    if key not in _frames:
        if len(_frames) > 32:
            _frames.clear()
        _frames[key] = codec.frame(dims)
    return _frames[key]


def lsh(nbits: int, seed: int = 1, rotate: bool = True, hashed: bool = False, thresholds: str = "zero") -> Codec:
    return Lsh(f"lsh_{nbits}" + ("_hashed" if hashed else ""), nbits, seed, rotate, hashed, thresholds)


@dataclass(frozen=True)
class Pq(Codec):
    """Product quantization: the nearest centroid in each of m subspaces. Codebook: m x 2^width x (dims / m)."""

    m: int = 8
    width: int = 8
    symmetric: bool = True

    def encode(self, x, c):
        parts = x.reshape(len(x), self.m, -1)
        return np.stack([nearest(parts[:, s], c.codebook[s])[0] for s in range(self.m)], axis=1).astype(np.float64)

    def space(self, code, c):
        at = code.astype(np.int64)
        return np.concatenate([c.codebook[s][at[:, s]] for s in range(self.m)], axis=1)

    def bits(self, dims, native=32):
        return self.m * self.width


def pq(m: int, width: int, symmetric: bool = True) -> Codec:
    return Pq(f"pq_{m}x{width}" + ("" if symmetric else "_raw_query"), m, width, symmetric)


def fit_lsh(df: DataFrame, codec: Lsh, id_col: str = "vec_id", vec_col: str = "embedding", method: str = "exact") -> Calibration:
    """Medians of every projection, for thresholds="median": each bit then splits the vectors in half."""
    from .calibrate import quantiles

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), V.lists(V.matrix(b.column(1)) @ _frame(codec, V.matrix(b.column(1)).shape[1]).T)], names=[id_col, "projected"])

    projected = df.select(id_col, vec_col).mapInArrow(run, f"{id_col} long, projected array<double>")
    return Calibration(codebook=quantiles(projected, (0.5,), "projected", method).at(0.5))


BLOCK = 1 << 17  # distances that are computed at once, so that they stay in a core's cache


def nearest(points: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of the nearest centre, squared distance to it) of every point; the first of equally near ones."""
    size = (centres**2).sum(axis=1)[None, :]
    near, least = np.empty(len(points), np.int64), np.empty(len(points))
    step = max(1, BLOCK // len(centres))
    for at in range(0, len(points), step):
        p = np.ascontiguousarray(points[at : at + step])
        far = (2 * p) @ centres.T
        np.subtract((p**2).sum(axis=1)[:, None], far, out=far)
        far += size
        near[at : at + step] = own = far.argmin(axis=1)
        least[at : at + step] = far[np.arange(len(p)), own]
    return near, least


def _distinct(points: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct points, place of each point among them, how many are equal); all points where few are equal."""
    key = np.zeros(len(points), np.int64)
    for column in points.T:
        values, own = np.unique(column, return_inverse=True)
        kinds, key = np.unique(key * len(values) + own, return_inverse=True)
        if len(kinds) > 0.7 * len(points):
            return points, np.arange(len(points)), np.ones(len(points), np.int64)
    _, first, weight = np.unique(key, return_index=True, return_counts=True)
    return points[first], key, weight


def lloyd(points: np.ndarray, centres: np.ndarray, rounds: int) -> np.ndarray:
    """k-means in squared distance; an empty centre is put on the point farthest from its own.

    Equal points are measured once and weigh as many as they are.
    """
    distinct, place, weight = _distinct(points)
    for _ in range(rounds):
        near, least = nearest(distinct, centres)
        n = np.bincount(near, weights=weight, minlength=len(centres))
        sums = np.stack([np.bincount(near, weights=distinct[:, j] * weight, minlength=len(centres)) for j in range(points.shape[1])], axis=1)
        fresh = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centres)
        empty = np.flatnonzero(n == 0)
        if len(empty) and len(points) > len(centres):
            fresh[empty] = points[np.argsort(-least[place], kind="stable")[: len(empty)]]
        if np.allclose(fresh, centres, rtol=0, atol=1e-12):
            break
        centres = fresh
    return centres


def train_pq(df: DataFrame, m: int, width: int, rounds: int = 25, id_col: str = "vec_id", vec_col: str = "embedding", sample: int | None = None, seed: int = 0, read=V.matrix) -> Calibration:
    """Codebooks from a hash sample of about 256 * 2^width vectors; each subspace is trained inside one task.

    read: what makes a matrix of the Arrow column vec_col.
    """
    sample = sample or 256 * 2**width
    n = df.count()
    from .calibrate import hash_sample

    rows = df.select(id_col, vec_col) if n <= sample else hash_sample(df.select(id_col, vec_col), id_col, sample / n, seed)
    k = 2**width

    def split(batches):
        for b in batches:
            x = read(b.column(1))
            if not len(x):
                continue
            parts = x.reshape(len(x), m, -1).transpose(1, 0, 2)
            ids = np.broadcast_to(b.column(0).to_numpy(), (m, len(x)))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(m, dtype=np.int32)), V.lists(ids, pa.int64()), V.lists(parts.reshape(m, -1))], names=["sub", "ids", "parts"])

    def fit(table: pa.Table) -> pa.Table:
        ids = np.concatenate([c.flatten().to_numpy() for c in table.column("ids").chunks])
        flat = np.concatenate([c.flatten().to_numpy() for c in table.column("parts").chunks])
        points = flat.reshape(len(ids), -1)[np.lexsort((ids,))]
        start = np.random.Generator(np.random.Philox(key=[seed, int(table.column("sub")[0].as_py())])).permutation(len(points))[:k]
        centres = points[np.sort(start)]
        if len(centres) < k:
            centres = np.concatenate([centres, np.repeat(centres[-1:], k - len(centres), axis=0)])
        centres = lloyd(points, centres, rounds)
        return pa.table([pa.array(np.full(k, table.column("sub")[0].as_py(), np.int32)), pa.array(np.arange(k, dtype=np.int32)), V.lists(centres)], names=["sub", "code", "centre"])

    # a stated number of partitions, as subspaces are few bytes and long work, and would be put together in few tasks
    book = rows.mapInArrow(split, "sub int, ids array<long>, parts array<double>").repartition(m, "sub").groupBy("sub").applyInArrow(fit, "sub int, code int, centre array<double>")
    found = sorted(book.collect(), key=lambda r: (r["sub"], r["code"]))  # 2^width x dims numbers
    return Calibration(codebook=np.array([r["centre"] for r in found]).reshape(m, k, -1))


def distributed_lloyd_step(df: DataFrame, c: Calibration, m: int, width: int, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """sub, code, pos, centre: means of all vectors' parts by nearest centroid, one shuffle of partial sums."""
    shared = df.sparkSession.sparkContext.broadcast(c)
    codec = pq(m, width)
    k = 2**width

    def run(batches):
        total = count = None
        for b in batches:
            x = V.matrix(b.column(0))
            if not len(x):
                continue
            code = codec.encode(x, shared.value).astype(np.int64)
            parts = x.reshape(len(x), m, -1)
            if total is None:
                total, count = np.zeros((m, k, parts.shape[2])), np.zeros((m, k), np.int64)
            for s in range(m):
                np.add.at(total[s], code[:, s], parts[:, s])
                count[s] += np.bincount(code[:, s], minlength=k)
        if total is not None:
            s, j, p = np.nonzero(np.repeat(count[:, :, None] > 0, total.shape[2], axis=2))
            yield pa.RecordBatch.from_arrays([pa.array(s.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(p.astype(np.int32)), pa.array(total[s, j, p]), pa.array(count[s, j])], names=["sub", "code", "pos", "total", "n"])

    sums = df.select(vec_col).mapInArrow(run, "sub int, code int, pos int, total double, n long")
    return sums.groupBy("sub", "code", "pos").agg((F.sum("total") / F.sum("n")).alias("centre"))


def encode(df: DataFrame, codec: Codec, c: Calibration, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """id, code (array<double>) of every vector: the narrow write path of codes."""
    shared = df.sparkSession.sparkContext.broadcast(c)

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), V.lists(codec.encode(V.matrix(b.column(1)), shared.value))], names=[id_col, "code"])

    return df.select(id_col, vec_col).mapInArrow(run, f"{id_col} long, code array<double>")


def packed(df: DataFrame, codec: Codec, c: Calibration, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """id, code (binary) in the codec's storage form: what a sink keeps, `bits` long up to the last byte."""
    shared = df.sparkSession.sparkContext.broadcast(c)

    def run(batches):
        for b in batches:
            if b.num_rows:
                code = codec.encode(V.matrix(b.column(1)), shared.value)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([to_bytes(codec, r) for r in code], pa.binary())], names=[id_col, "code"])

    return df.select(id_col, vec_col).mapInArrow(run, f"{id_col} long, code binary")


def to_bytes(codec: Codec, code: np.ndarray) -> bytes:
    inner = codec.then if isinstance(codec, Truncate) else codec
    if isinstance(inner, FloatCast):
        return R.pack_floats(code, inner.form).tobytes()
    if isinstance(inner, (Binary, Lsh)):
        return np.packbits(code.astype(np.uint8)).tobytes()
    if isinstance(inner, (Bins, Pq)):
        width = inner.width
        bits = (code.astype(np.int64)[:, None] >> np.arange(width - 1, -1, -1)) & 1
        return np.packbits(bits.astype(np.uint8).ravel()).tobytes()
    return code.astype("<f4").tobytes()
