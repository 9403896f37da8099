"""Nearest neighbours by inner product from randomly rotated one-bit codes, with reranking by error bounds.

A unit vector o, padded with zeros to `bits` dimensions, is rotated by a fixed random rotation and kept as the signs of
its coordinates. With x the sign vector over sqrt(bits) and c = <x, o>, the inner product <o, q> of a rotated unit query q
is estimated by <x, q> / c, and the estimate's error is below spread * sqrt(1 - c^2) / c / sqrt(bits - 1) with high
probability.

index() writes one row for every distinct vector: the packed bits, the norm and c, and beside them the vector and the
k + 1 smallest ids that hold it (ties go to the smaller id, so more are never needed, and a vector that a third of all
rows share costs no more than another). search() then goes in three steps. (1) Only codes, norms and c move: blocks of
them meet blocks of queries, and the k + 1 best estimates of a query, multiplied exactly, give a floor that its k-th best
cannot be below. (2) The codes are scanned once more: a query's candidates are the vectors whose upper bound reaches its
floor; they stay lists, one a query and block. (3) The vectors that are a candidate of some query of a query block, and no
others, are sent to that block's lists and multiplied in double precision. Signs are unpacked a slice at a time for a
matrix product, as numpy has no faster use of packed bits: the code saves the traffic of vectors, not these products.

Norms are taken relative to the largest component, so no finite vector overflows; a vector whose norm is beyond the
largest double is always reranked. Scores are sums in the order of dimensions in double precision.

Vectors that are null, empty, zero, or hold nulls or non-finite values take no part, and nor do rows without an id;
vectors are compared with those of their own length only. Rows that repeat an id count once: the smallest vector of them
is kept. A query never finds its own id. Fewer than k candidates: all of them. Empty tables give no rows. Extra columns are
not read. The work is rows times queries: random vectors have no cells that would spare any of it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

BITS, SPREAD, BLOCK, QUERIES = 256, 3.0, 1 << 17, 1 << 13
SLACK = 1e-5  # rounding of estimates, as a share of the norm


def rotation(bits: int, seed: int = 20240501) -> np.ndarray:
    """A random orthogonal matrix, the same in every process."""
    g = np.random.Generator(np.random.Philox(seed)).standard_normal((bits, bits))
    q, r = np.linalg.qr(g)
    return q * np.sign(np.diag(r))


def code_bits(dims: int, least: int = BITS) -> int:
    return max(least, -(-dims // 64) * 64)


def unit(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vectors of norm 1, norms); the norm alone may be infinite."""
    top = np.abs(vectors).max(axis=1, initial=0.0)
    scaled = vectors / top[:, None]
    length = np.sqrt((scaled * scaled).sum(axis=1))
    with np.errstate(over="ignore"):
        return scaled / length[:, None], top * length


def encode(vectors: np.ndarray, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(packed bits, norms, c) of the rows of a matrix."""
    own, norm = unit(vectors)
    rotated = own @ turn[: vectors.shape[1]]
    return np.packbits(rotated > 0, axis=1), norm, np.abs(rotated).sum(axis=1) / np.sqrt(len(turn))


def estimates(packed: np.ndarray, norm: np.ndarray, along: np.ndarray, queries: np.ndarray, turn: np.ndarray) -> np.ndarray:
    """Estimated inner products with unit queries: queries x rows."""
    turned = (unit(queries)[0] @ turn[: queries.shape[1]]).astype(np.float32)
    out = np.empty((len(queries), len(packed)))
    for at in range(0, len(packed), 8192):
        part = slice(at, at + 8192)
        out[:, part] = turned @ (np.unpackbits(packed[part], axis=1).astype(np.float32) * 2 - 1).T
    with np.errstate(over="ignore", invalid="ignore"):
        out *= norm / (along * np.sqrt(len(turn)))
    out[:, ~np.isfinite(norm)] = np.inf
    return out


def errors(norm: np.ndarray, along: np.ndarray, bits: int, spread: float = SPREAD) -> np.ndarray:
    """How far an estimate for a unit query may be from the inner product."""
    with np.errstate(over="ignore", invalid="ignore"):
        return norm * (spread * np.sqrt(np.maximum(0, 1 - along**2)) / along / np.sqrt(bits - 1) + SLACK)


def exact(queries: np.ndarray, qi: np.ndarray, vectors: np.ndarray, vi: np.ndarray) -> np.ndarray:
    """Inner products of pairs in double precision, summed in the order of dimensions."""
    out = np.zeros(len(qi))
    with np.errstate(over="ignore", invalid="ignore"):
        for at in range(0, len(qi), 1 << 15):
            p = slice(at, at + (1 << 15))
            parts = queries[qi[p]] * vectors[vi[p]]
            total = np.zeros(len(parts))
            for j in range(parts.shape[1]):
                total += parts[:, j]
            out[p] = total
    return out


def sound(vec: Column) -> Column:
    """True for vectors that take part."""
    finite = F.forall(vec, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
    return F.coalesce(vec.isNotNull() & (F.size(vec) > 0) & finite & F.exists(vec, lambda v: v != 0), F.lit(False))


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    values = pa.concat_arrays(column.chunks) if isinstance(column, pa.ChunkedArray) else column
    return values.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(values), -1)


def _bytes(column: pa.ChunkedArray) -> np.ndarray:
    raw = pa.concat_arrays(column.chunks) if isinstance(column, pa.ChunkedArray) else column
    return np.frombuffer(b"".join(raw.to_pylist()), np.uint8).reshape(len(raw), -1)


def _lists(values: np.ndarray, sizes: np.ndarray, kind: pa.DataType) -> pa.Array:
    offsets = np.zeros(len(sizes) + 1, dtype=np.int32)
    np.cumsum(sizes, out=offsets[1:])
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(values, kind))


def _renewed(df: DataFrame) -> DataFrame:
    """df under column identities of its own, for a cogroup with a table that it comes from."""
    return df.select(*(F.col(c).alias(c) for c in df.columns))


def sound_rows(vectors: DataFrame) -> DataFrame:
    """vec_id, vec (array<double>), dims of the vectors that take part, one row an id."""
    rows = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("vec")).where(F.col("vec_id").isNotNull() & sound(F.col("vec")))
    return rows.groupBy("vec_id").agg(F.min("vec").alias("vec")).withColumn("dims", F.size("vec"))


def index(vectors: DataFrame, k: int = 20, bits: int = BITS, block: int = BLOCK, slices: int = 8) -> DataFrame:
    """rep, dims, rb, packed, norm, along, vec, ids of every distinct vector, as a written table.

    rep is the smallest id that holds the vector, ids the k + 1 smallest, rb the block of about `block` rows (at least
    `slices` blocks, so that small tables use all cores).
    """
    rows = C.materialize(sound_rows(vectors), "onebit-rows")
    blocks = max(slices, -(-rows.count() // block))
    place = F.row_number().over(Window.partitionBy("vec").orderBy("vec_id"))
    # the group limit keeps k + 1 ids of a vector in every task before anything is shuffled
    few = rows.withColumn("place", place).where(F.col("place") <= k + 1)
    distinct = few.groupBy("vec", "dims").agg(F.sort_array(F.collect_list("vec_id")).alias("ids")).withColumn("rep", F.col("ids")[0])
    dealt = distinct.select("rep", "dims", F.pmod(F.xxhash64("rep"), F.lit(blocks)).cast("int").alias("rb"), "vec", "ids")

    def code(batches):
        turns: dict[int, np.ndarray] = {}
        for b in batches:
            dims = b.column("dims").to_numpy()
            packed, norm, along = [b""] * len(dims), np.zeros(len(dims)), np.zeros(len(dims))
            for d in np.unique(dims).tolist():
                at = np.flatnonzero(dims == d)
                turn = turns.setdefault(d, rotation(code_bits(d, bits)))
                own, norm[at], along[at] = encode(_matrix(b.column("vec").take(pa.array(at))), turn)
                for i, p in zip(at.tolist(), own):
                    packed[i] = p.tobytes()
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("rep", "dims", "rb")), pa.array(packed, pa.binary()), pa.array(norm), pa.array(along), b.column("vec"), b.column("ids")], names=["rep", "dims", "rb", "packed", "norm", "along", "vec", "ids"])

    return C.materialize(dealt.mapInArrow(code, "rep long, dims int, rb int, packed binary, norm double, along double, vec array<double>, ids array<long>"), "onebit-index")


def _block(left: pa.Table, right: pa.Table, bits: int):
    """Codes of a block, its queries 64 at a time with their estimates: (reps, norm, along, bits), and an iterator."""
    reps, norm, along, packed = left.column("rep").to_numpy(), left.column("norm").to_numpy(), left.column("along").to_numpy(), _bytes(left.column("packed"))
    ids, q = right.column("query_id").to_numpy(), _matrix(right.column("vec"))
    turn = rotation(code_bits(q.shape[1], bits))
    return reps, norm, along, len(turn), ((slice(at, at + 64), ids[at : at + 64], q[at : at + 64], estimates(packed, norm, along, q[at : at + 64], turn)) for at in range(0, len(q), 64))


def search(vectors: DataFrame, queries: DataFrame, k: int = 20, bits: int = BITS, spread: float = SPREAD, block: int = BLOCK, slices: int = 8) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k nearest among vectors(vec_id, embedding)."""
    table = index(vectors, k, bits, block, slices)
    asked = C.materialize(sound_rows(queries).withColumnRenamed("vec_id", "query_id"), "onebit-queries")
    query_blocks = max(1, -(-asked.count() // QUERIES))
    asked = asked.withColumn("qb", F.pmod(F.xxhash64("query_id"), F.lit(query_blocks)).cast("int"))
    places = C.materialize(table.select("dims", "rb").distinct(), "onebit-blocks")  # one row a block
    keys = ["dims", "rb", "qb"]
    codes = table.select("rep", "dims", "rb", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))).alias("qb"), "packed", "norm", "along")

    def top(left: pa.Table, right: pa.Table) -> pa.Table:
        """The k + 1 best estimates of every query in a block."""
        found = [[np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]]
        if left.num_rows and right.num_rows:
            reps, _, _, _, parts = _block(left, right, bits)
            n = min(k + 1, len(reps))
            for _, ids, _, estimate in parts:
                best = np.argpartition(-estimate, n - 1, axis=1)[:, :n]
                found.append([np.repeat(ids, n), reps[best.ravel()], np.take_along_axis(estimate, best, axis=1).ravel()])
        return pa.table([pa.array(np.concatenate(c)) for c in zip(*found)], names=["query_id", "rep", "estimate"])

    likely = codes.groupBy(*keys).cogroup(_renewed(asked.join(places, "dims")).groupBy(*keys)).applyInArrow(top, "query_id long, rep long, estimate double")
    order = Window.partitionBy("query_id").orderBy(F.desc("estimate"), "rep")
    likely = likely.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k + 1).select("query_id", "rep")
    # the exact values of k + 1 vectors: the k-th best cannot be below the least of them, even if one is the query itself
    product = F.aggregate(F.zip_with("vec", "own", lambda a, b: a * b), F.lit(0.0), lambda total, x: total + x)
    pairs = likely.join(table.select("rep", "vec"), "rep").join(asked.select("query_id", F.col("vec").alias("own")), "query_id")
    floors = pairs.groupBy("query_id").agg(F.min(F.nanvl(product, F.lit(float("-inf")))).alias("floor"), F.count("*").alias("n")).where(F.col("n") > k).select("query_id", "floor")
    floored = C.materialize(asked.join(floors, "query_id", "left").select("query_id", "vec", "dims", "qb", F.coalesce("floor", F.lit(float("-inf"))).alias("floor")), "onebit-floors")

    def candidates(left: pa.Table, right: pa.Table) -> pa.Table:
        """The vectors of a block whose upper bound reaches a query's floor; and, without a query, all that any of them needs."""
        ids_out, lists, needed = [], [], np.zeros(0, bool)
        if left.num_rows and right.num_rows:
            floor = right.column("floor").to_numpy()
            reps, norm, along, width, parts = _block(left, right, bits)
            error, needed = errors(norm, along, width, spread), np.zeros(len(reps), bool)
            for at, ids, q, estimate in parts:
                with np.errstate(over="ignore", invalid="ignore"):
                    least = floor[at] / unit(q)[1]
                    reach = estimate + error >= (least - SLACK * np.abs(least))[:, None]
                reach[:, ~np.isfinite(norm)] = True
                reach[~np.isfinite(least)] = True
                qi, vi = np.nonzero(reach)
                needed[vi] = True
                many = np.bincount(qi, minlength=len(ids))
                ids_out.append(pa.array(ids[many > 0], pa.int64()))
                lists.append(_lists(reps[vi], many[many > 0], pa.int64()))
            ids_out.append(pa.array([None], pa.int64()))
            lists.append(_lists(reps[needed], np.array([needed.sum()]), pa.int64()))
        columns = [pa.concat_arrays(ids_out), pa.concat_arrays(lists)] if ids_out else [pa.array([], pa.int64()), pa.array([], pa.list_(pa.int64()))]
        side = {c: pa.array(np.full(len(columns[0]), right.column(c)[0].as_py() if right.num_rows else 0, np.int32)) for c in keys}
        return pa.table([*columns, *side.values()], names=["query_id", "reps", *keys])

    scanned = codes.groupBy(*keys).cogroup(_renewed(floored.join(places, "dims")).groupBy(*keys)).applyInArrow(candidates, "query_id long, reps array<long>, dims int, rb int, qb int")
    scanned = C.materialize(scanned, "onebit-candidates")
    needed = scanned.where("query_id is null").select(*keys, F.explode("reps").alias("rep"))  # a vector once a block of queries at most
    sent = needed.join(table.select("rep", "vec", "ids"), "rep")
    requests = scanned.where("query_id is not null").join(asked.select("query_id", "vec"), "query_id")

    def rerank(left: pa.Table, right: pa.Table) -> pa.Table:
        found = [[np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]]
        if left.num_rows and right.num_rows:
            reps, v = left.column("rep").to_numpy(), _matrix(left.column("vec"))
            by = np.argsort(reps)
            reps, v = reps[by], v[by]
            owners = left.column("ids").to_pylist()
            owners = [owners[i] for i in by.tolist()]
            begin = np.concatenate([[0], np.cumsum([len(o) for o in owners])])
            names = np.array([i for o in owners for i in o], dtype=np.int64)
            ids, q, lists = right.column("query_id").to_numpy(), _matrix(right.column("vec")), right.column("reps").to_pylist()
            for i, own in enumerate(lists):
                vi = np.searchsorted(reps, np.array(own, dtype=np.int64))
                score = exact(q, np.full(len(vi), i), v, vi)
                score[np.isnan(score)] = -np.inf
                if len(vi) > 4 * (k + 1):  # distinct vectors: the k + 1 best scores hold the k best ids
                    top = score >= np.partition(score, len(score) - k - 1)[len(score) - k - 1]
                    vi, score = vi[top], score[top]
                # back to ids: every vector stands for its kept ids
                times = begin[vi + 1] - begin[vi]
                row = np.repeat(np.arange(len(vi)), times)
                name = names[begin[vi[row]] + np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)]
                score, other = score[row], name != ids[i]
                name, score = name[other], score[other]
                best = np.lexsort((name, -score))[:k]
                found.append([np.full(len(best), ids[i]), name[best], score[best]])
        return pa.table([pa.array(np.concatenate(c)) for c in zip(*found)], names=["query_id", "vec_id", "score"])

    near = sent.groupBy(*keys).cogroup(_renewed(requests).groupBy(*keys)).applyInArrow(rerank, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def brute_force(ids: np.ndarray, vectors: np.ndarray, query_ids, k: int) -> Iterator[tuple]:
    """The answer that search must give, on small inputs."""
    place = {int(i): n for n, i in enumerate(ids)}
    for q in query_ids:
        score = exact(vectors.astype(np.float64), np.full(len(ids), place[int(q)]), vectors.astype(np.float64), np.arange(len(ids)))
        order = [i for i in np.lexsort((ids, -score)) if ids[i] != q][:k]
        for r, i in enumerate(order, 1):
            yield int(q), r, int(ids[i]), float(score[i])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = C.table(spark, sf_dir, "embeddings")
    return search(table, table.where(F.col("vec_id") % 20 == 0))
