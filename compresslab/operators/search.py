"""Exact retrieval by cosine over codes.

topk_sql states the search in relational terms, for checks and small corpora. topk_fused is the scale path: one
Arrow scan over the native vectors encodes each batch with every codec, multiplies it with the encoded
queries and keeps k rows per codec, tier shell and query in a task; only these are shuffled. As tiers nest, the
result for a tier is the merge of the shells up to it, so all tiers cost one scan too.

Order: score rounded to 9 digits, larger first, then the smaller id. A zero vector has cosine 0.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from .calibrate import Calibration
from .codecs import Codec, Pq, family, identity, signed

DIGITS = 9
QUERY_CHUNK = 4096  # queries that a scan carries at most; more of them make more scans
HELD = 1 << 22  # rows that a task may hold for all its codecs, tiers and queries (four times that before a cut)
CELLS = 1 << 22  # scores that are computed at once
VALUES = 1 << 21  # values of vectors that are encoded at once
KNOWN_CHUNK = 16384  # queries of known items that a scan carries; every scan encodes the items again
KNOWN_ROWS, TILE = 1024, 512  # items and queries that are compared at once: their scores stay in a core's cache
PAIRS = 4096  # pairs that are compared again at once in double precision


def topk_sql(queries: DataFrame, items: DataFrame, k: int = 100) -> DataFrame:
    """query_id, item_id, rank, score from queries(query_id, vec) and items(item_id, vec).

    The queries are broadcast by Spark while they are below its threshold; the group limit before the exchange keeps k rows a task.
    """
    scored = items.crossJoin(queries.withColumnRenamed("vec", "q")).select("query_id", "item_id", F.round(V.cosine(F.col("q"), F.col("vec")), DIGITS).alias("score"))
    return rank(scored, k)


def rank(scored: DataFrame, k: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """keys..., query_id, item_id, rank, score: the k best of every query."""
    order = Window.partitionBy(*keys, "query_id").orderBy(F.desc("score"), "item_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(*keys, "query_id", "item_id", "rank", "score")


def _unit(x: np.ndarray) -> np.ndarray:
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size > 0)


class _Held:
    """The k best of every query so far: flat arrays that are cut back to k a query when they grow to four times that."""

    def __init__(self, queries: int, k: int, least: float = -np.inf):
        self.k, self.queries = k, queries
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.rows, self.floor = 0, np.full(queries, least)

    def add(self, score: np.ndarray, ids: np.ndarray) -> None:
        """score: queries x ids. Only what may still be among the k best is kept; ties at the edge all are."""
        floor = self.floor
        if score.shape[1] > 4 * self.k:
            floor = np.maximum(floor, np.partition(score, score.shape[1] - self.k, axis=1)[:, score.shape[1] - self.k])
        qi, at = np.nonzero(score >= floor[:, None])
        self.parts.append((qi, ids[at], score[qi, at]))
        self.rows += len(qi)
        if self.rows > 4 * self.k * self.queries:
            self.cut()

    def cut(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        qi, ids, score = (np.concatenate(c) for c in zip(*self.parts))
        order = np.lexsort((ids, -score, qi))
        qi, ids, score = qi[order], ids[order], score[order]
        place = np.arange(len(qi)) - np.searchsorted(qi, qi)
        keep = place < self.k
        last = place == self.k - 1
        self.floor[qi[last]] = score[last]
        self.parts = [(qi[keep], ids[keep], score[keep])]
        self.rows = len(self.parts[0][0])
        return self.parts[0]


def topk_fused(
    queries: tuple[np.ndarray, np.ndarray], items: DataFrame, variants: list[tuple[Codec, Calibration | dict[int, Calibration]]], k: int = 100,
    tiers: int = 1, id_col: str = "vec_id", vec_col: str = "embedding", tier_col: str | None = None, batch_col: str | None = None, read=V.matrix,
) -> DataFrame:
    """variant, tier, query_id, item_id, rank, score for every codec and tier from one scan.

    queries: (ids, matrix). tier_col: the smallest tier (1..tiers) that holds an item. A variant whose calibration is a
    dict is calibrated per batch: items of batch b, and the queries against them, are encoded with entry b. read: what makes
    a matrix of the Arrow column vec_col; with an encoder there, texts are encoded in the scan itself.
    """
    ids, matrix = queries
    chunk = max(16, min(QUERY_CHUNK, HELD // (len(variants) * tiers * k)))
    parts = [_scan((ids[at : at + chunk], matrix[at : at + chunk]), items, variants, k, id_col, vec_col, tier_col, batch_col, read) for at in range(0, max(1, len(ids)), chunk)]
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    names = F.array(*(F.lit(c.name) for c, _ in variants))
    in_tiers = found.select(F.element_at(names, F.col("variant") + 1).alias("variant"), F.explode(F.sequence("shell", F.lit(tiers))).alias("tier"), "query_id", "item_id", "score")
    return rank(in_tiers, k, ("variant", "tier"))


def _scan(queries, items, variants, k, id_col, vec_col, tier_col, batch_col, read=V.matrix) -> DataFrame:
    spark = items.sparkSession
    shared = spark.sparkContext.broadcast((queries, variants))
    columns = [F.col(id_col).cast("long"), F.col(vec_col), (F.col(tier_col) if tier_col else F.lit(1)).cast("int").alias("__tier"), (F.col(batch_col) if batch_col else F.lit(0)).cast("int").alias("__batch")]

    def run(batches):
        (qids, q), codecs = shared.value
        encoded: dict = {}
        held: dict[tuple[int, int], _Held] = {}

        def queries_of(v: int, batch: int) -> np.ndarray:
            codec, c = codecs[v]
            key = (v, batch if isinstance(c, dict) else 0)
            if key not in encoded:
                c = c[batch] if isinstance(c, dict) else c
                raw = isinstance(codec, Pq) and not codec.symmetric
                encoded[key] = _unit(q if raw else codec.space(codec.encode(q, c), c))
            return encoded[key]

        step = max(256, min(CELLS // max(1, len(qids)), VALUES // max(1, q.shape[-1])))
        for whole in batches:
            for start in range(0, whole.num_rows, step):
                b = whole.slice(start, step)
                x, own, shell, batch = read(b.column(1)), b.column(0).to_numpy(), b.column(2).to_numpy(), b.column(3).to_numpy()
                for v, (codec, c) in enumerate(codecs):
                    for g in np.unique(batch) if isinstance(c, dict) else [None]:
                        rows = np.arange(len(x)) if g is None else np.flatnonzero(batch == g)
                        cal = c if g is None else c[int(g)]
                        unit = _unit(codec.space(codec.encode(x[rows], cal), cal))
                        score = np.round(queries_of(v, 0 if g is None else int(g)) @ unit.T, DIGITS)
                        for t in np.unique(shell[rows]):
                            at = np.flatnonzero(shell[rows] == t)
                            held.setdefault((v, int(t)), _Held(len(qids), k)).add(score[:, at], own[rows[at]])
        for (v, t), best in held.items():
            qi, found, score = best.cut()
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(qi), v, np.int32)), pa.array(np.full(len(qi), t, np.int32)), pa.array(np.asarray(qids, np.int64)[qi]), pa.array(found), pa.array(score)],
                names=["variant", "shell", "query_id", "item_id", "score"])

    return items.select(*columns).mapInArrow(run, "variant int, shell int, query_id long, item_id long, score double")


def known_items(queries: tuple[np.ndarray, np.ndarray], own: np.ndarray, items: DataFrame, variants: list[tuple[Codec, Calibration]], k: int = 100, id_col: str = "vec_id", vec_col: str = "embedding", read=V.matrix) -> DataFrame:
    """variant, query_id, found: whether the item of a query's own id is among its k best, in the order of topk_fused.

    own: the native vectors of these items. Items that come before it are counted, so a task keeps a number for each codec and
    query, not k rows; a query with k of them in a task is settled, and is not compared further there. read: what makes a matrix
    of the Arrow column vec_col.
    """
    ids, matrix = queries
    parts = []
    for at in range(0, max(1, len(ids)), KNOWN_CHUNK):
        parts.append(_before((ids[at : at + KNOWN_CHUNK], matrix[at : at + KNOWN_CHUNK], own[at : at + KNOWN_CHUNK]), items, variants, k, id_col, vec_col, read))
    counted = parts[0]
    for p in parts[1:]:
        counted = counted.unionByName(p)
    names = F.array(*(F.lit(c.name) for c, _ in variants))
    return counted.groupBy("variant", "query_id").agg(F.sum("n").alias("n")).select(F.element_at(names, F.col("variant") + 1).alias("variant"), "query_id", (F.col("n") < k).alias("found"))


class _Known:
    """Queries of known items under codecs whose codes are prefixes of the widest one's, mostly of a single codec.

    Products are made in single precision. Those of +1 and -1 are whole numbers and exact; others are off by less than `slack`,
    and scores within it of a query's own are made again in double precision from the codes.
    """

    def __init__(self, members: list[tuple[int, Codec, Calibration]], ids: np.ndarray, matrix: np.ndarray, code: np.ndarray | None, marks: np.ndarray):
        """code, marks: of made(), for all queries."""
        self.at = [v for v, _, _ in members]
        self.codec, self.c = members[-1][1:]
        self.raw, self.signed, self.ids, self.rows = _raw(self.codec), signed(self.codec), ids, np.arange(len(ids))
        kind, q = np.int8 if self.signed else np.float32, []
        for start in range(0, len(ids), 1024):
            part = (matrix if self.raw else self.codec.encode(matrix[start : start + 1024], self.c)) if code is None else code[start : start + 1024]
            q.append(self._space(part[:1024], self.raw).astype(kind))
        self.q, self.marks = np.concatenate(q), marks
        self.code = None if self.signed else code if code is not None else matrix if self.raw else self.codec.encode(matrix, self.c)
        self.widths = _widths(members, self.q.shape[1])
        if self.signed:
            self.low = (self.marks - 0.5).astype(np.float32)
            return
        self.marks = np.round(self.marks, DIGITS)
        self.slack = 10.0**-DIGITS + (self.q.shape[1] + 16) * 2.0**-23  # twice the bound of a product of unit vectors
        self.low = (self.marks - self.slack).astype(np.float32)

    @staticmethod
    def made(members, matrix: np.ndarray, own: np.ndarray) -> tuple[np.ndarray | None, np.ndarray]:
        """(codes of queries, none where they are a part of the vectors; products of queries with their own items by codec)."""
        codec, c = members[-1][1:]
        raw = _raw(codec)
        code = matrix if raw else codec.encode(matrix, c)
        whole = (lambda x: x) if signed(codec) else _unit
        mine, theirs = whole(code if raw else codec.space(code, c)), whole(codec.space(codec.encode(own, c), c))
        marks = np.stack([(mine[:, :w] * theirs[:, :w]).sum(axis=1) for w in _widths(members, mine.shape[1])])
        return None if np.may_share_memory(code, matrix) else code, marks

    def _space(self, code: np.ndarray, raw: bool = False) -> np.ndarray:
        code = code.astype(np.float64)
        if self.signed:
            return self.codec.space(code, self.c)
        return _unit(code if raw else self.codec.space(code, self.c))

    def count(self, x: np.ndarray, item: np.ndarray, before: np.ndarray, k: int) -> None:
        """Add to before (codecs x queries) how many of the vectors x come before a query's own item."""
        if not len(self.rows):
            return
        unit = self._space(self.codec.encode(x, self.c))
        narrow = unit.astype(np.float32)
        for start in range(0, len(self.rows), TILE):
            rows, q = self.rows[start : start + TILE], self.q[start : start + TILE].astype(np.float32, copy=False)
            score, done = None, 0
            for j, (v, w) in enumerate(zip(self.at, self.widths)):
                part = q[:, done:w] @ narrow[:, done:w].T
                score = part if score is None else np.add(score, part, out=score)
                done = w
                hit = _true(score > self.low[j, start : start + TILE, None])
                if not len(hit):
                    continue
                near, at = np.divmod(hit, len(x))
                value, target = score.ravel()[hit].astype(np.float64), self.marks[j, start + near]
                if not self.signed:
                    again = np.flatnonzero(np.abs(value - target) <= self.slack)
                    for cut in range(0, len(again), PAIRS):
                        e = again[cut : cut + PAIRS]
                        which, place = np.unique(start + near[e], return_inverse=True)
                        value[e] = np.round((self._space(self.code[which], self.raw)[place] * unit[at[e]]).sum(axis=1), DIGITS)
                mine = self.ids[rows[near]]
                first = ((value > target) | ((value == target) & (item[at] < mine))) & (item[at] != mine)
                before[v, rows] += np.bincount(near[first], minlength=len(rows))
        left = before[self.at][:, self.rows] < k
        self.low[~left] = np.inf  # settled under this codec
        alive = left.any(axis=0)
        if alive.mean() < 0.95:
            self.rows, self.q, self.low, self.marks = self.rows[alive], self.q[alive], self.low[:, alive], self.marks[:, alive]
            self.code = None if self.signed else self.code[alive]


def _raw(codec: Codec) -> bool:
    return isinstance(codec, Pq) and not codec.symmetric


def _widths(members, dims: int) -> list[int]:
    """How many dimensions of the widest codec's vectors each member has."""
    return [codec.nbits if len(members) > 1 else dims for _, codec, _ in members]


def _groups(variants: list[tuple[Codec, Calibration]], dims: int) -> list[list[tuple[int, Codec, Calibration]]]:
    groups: dict = {}
    for v, (codec, c) in enumerate(variants):
        groups.setdefault(family(codec, dims) or v, []).append((v, codec, c))
    return [sorted(g, key=lambda m: m[1].nbits) if len(g) > 1 else g for g in groups.values()]


def _small(code: np.ndarray) -> np.ndarray:
    """The same codes, in a byte each where they are small whole numbers."""
    byte = code.astype(np.uint8) if code.size and code.min() >= 0 and code.max() <= 255 else None
    return byte if byte is not None and (byte == code).all() else code


def _true(hit: np.ndarray) -> np.ndarray:
    """The places of the true cells, which are few."""
    flat = hit.ravel()
    words = flat[: len(flat) // 8 * 8].view(np.uint64)
    cells = (np.flatnonzero(words)[:, None] * 8 + np.arange(8)).ravel()
    rest = np.arange(len(words) * 8, len(flat))
    return np.concatenate([cells[flat[cells]], rest[flat[rest]]])


def _before(queries, items, variants, k, id_col, vec_col, read=V.matrix) -> DataFrame:
    context = items.sparkSession.sparkContext
    shared = context.broadcast((queries, variants))

    def encode(start):
        (_, matrix, own), codecs = shared.value
        made = [_Known.made(g, matrix[start : start + TILE], own[start : start + TILE]) for g in _groups(codecs, matrix.shape[-1])]
        return [(None if code is None else _small(code), marks) for code, marks in made]

    # queries and their own items are encoded once, not in every task
    starts = range(0, len(queries[0]), TILE)
    parts = context.parallelize(starts, len(starts)).map(encode).collect() if len(starts) else []
    codes = context.broadcast([(None if own[0][0] is None else np.concatenate([c for c, _ in own]), np.concatenate([m for _, m in own], axis=1)) for own in zip(*parts)])
    del parts

    def run(batches):
        (ids, matrix, _), codecs = shared.value
        state = None
        before = np.zeros((len(codecs), len(ids)), np.int64)
        for whole in batches:
            for start in range(0, whole.num_rows if len(ids) else 0, KNOWN_ROWS):
                b = whole.slice(start, KNOWN_ROWS)
                if state is None:
                    state = [_Known(g, ids, matrix, *made) for g, made in zip(_groups(codecs, matrix.shape[-1]), codes.value)]
                x, item = read(b.column(1)), b.column(0).to_numpy()
                for group in state:
                    group.count(x, item, before, k)
        v, at = np.divmod(np.arange(before.size), max(1, len(ids)))
        yield pa.RecordBatch.from_arrays([pa.array(v.astype(np.int32)), pa.array(np.asarray(ids, np.int64)[at]), pa.array(before.ravel())], names=["variant", "query_id", "n"])

    return items.select(F.col(id_col).cast("long"), vec_col).mapInArrow(run, "variant int, query_id long, n long")


def topk_arrow(queries: tuple[np.ndarray, np.ndarray], items: DataFrame, k: int = 100, codec: Codec | None = None, c: Calibration | None = None, **columns) -> DataFrame:
    """query_id, item_id, rank, score of one codec (none: native vectors)."""
    return topk_fused(queries, items, [(codec or identity(), c or Calibration())], k, **columns).drop("variant", "tier")


def topk_hamming(queries: DataFrame, items: DataFrame, k: int = 100) -> DataFrame:
    """query_id, item_id, rank, hamming from packed words(array<long>): the order of +1/-1 cosines."""
    scored = items.crossJoin(queries.withColumnRenamed("words", "q")).select("query_id", "item_id", V.hamming(F.col("q"), F.col("words")).cast("long").alias("hamming"))
    order = Window.partitionBy("query_id").orderBy("hamming", "item_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "item_id", "rank", "hamming")


def topk_bits_raw(queries: DataFrame, items: DataFrame, k: int = 100) -> DataFrame:
    """query_id, item_id, rank, score: cosine of 0/1 bits, common ones over the root of both counts."""
    scored = items.crossJoin(queries.withColumnRenamed("words", "q")).select(
        "query_id", "item_id", F.coalesce(F.round(F.try_divide(V.common_ones(F.col("q"), F.col("words")), F.sqrt(V.ones(F.col("q")) * V.ones(F.col("words")))), DIGITS), F.lit(0.0)).alias("score"))
    return rank(scored, k)


def collect_queries(queries: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids, matrix) of queries(query_id, vec), ordered by id. Query sets are stated inputs of tens to thousands of rows."""
    rows = queries.select("query_id", "vec").toArrow()
    ids, x = rows.column(0).to_numpy().astype(np.int64), V.matrix(rows.column(1))
    order = np.argsort(ids, kind="stable")
    return ids[order], x[order]
