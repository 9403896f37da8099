"""Near-copies: consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

A text is the set of its five-word shingles (the whole text, if it has fewer words); a shingle weighs its count in
the text times a smoothed inverse document frequency, SMOOTH + ln(documents / held) / ln(documents), where held is
the number of documents that hold it. These numbers are exact for every shingle. Documents are put together in
blocks, compressed; a block asks for each of its shingles once, in sorted runs, one to each range of shingles. A range adds up
what all blocks ask and answers each run with the numbers in its order. So rows that are shuffled are runs, no
shingle is hot, and neither a range nor a block grows with the corpus.

Improved consistent weighted sampling draws SAMPLES samples of every text, such that two texts agree in a sample
with a probability equal to their weighted Jaccard similarity. Texts that agree in all samples of a band share a
bucket. Within a bucket every member is compared with the pivot, the smallest member; links become components. Then,
as long as a bucket holds more than one component, members outside become pivots in turn, more of them each round,
and are compared with all members of other components. When this ends, every two members of a bucket are in one
component or have been compared, so no bucket is capped and no link within it is lost, and a group of n copies costs
n comparisons, not n squared. Pairs of members outside are first judged by a bound: the weights of a text are summed in
GROUPS groups of shingles, and sums never differ by more than the weights do, so texts whose sums differ too much for
SIMILAR are not similar; sums are rounded, and the bound leaves room for that. All pairs that it admits are verified.

Equal texts (64 bits of hash) are one node from the start. A null text, or one without a word, is like none but its
exact equals (null: none at all). Rows without a doc_id belong to no class. Repeated rows share a class. Empty tables
give no rows. Extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C
from . import words as W

SHINGLE, SIMILAR = 5, 0.8
SAMPLES, ROWS = 120, 6
BATCH = 256 << 10  # bytes of text at a time: the kernels' buffers stay in the cache
COMMON, SMOOTH = 0.0, 2.0  # the share of documents above which a shingle's own frequency counts: all do
BLOCK, RANGE, BLOCK_TASK, BLOCK_ROWS = 1 << 20, 1 << 20, 8, 4  # bytes of text in a block, shingles in a range, blocks of a task, blocks that are read or cross to Python at once
# a writer looks at the size of its pages every hundred rows, if it is not told otherwise: a page of blocks would be 100 MB; a page holds one
LARGE_ROWS = {"parquet.page.size.row.check.min": "1", "parquet.block.size.row.check.min": "1", "parquet.page.row.count.limit": "1"}
ZSTD = 3  # the level at which the texts of blocks are compressed
GROUPS, UNIT, MOST = 256, 64, 32767  # groups of a text's weights, steps of their sums to a unit of weight, largest sum
ID_BITS = 44
BROADCAST_ROWS = 4_000_000


def _gamma_table(size: int = 1 << 16) -> np.ndarray:
    """Quantiles of the Gamma(2, 1) distribution."""
    u = (np.arange(size) + 0.5) / size
    low, high = np.zeros(size), np.full(size, 60.0)
    for _ in range(60):
        x = (low + high) / 2
        under = 1 - (1 + x) * np.exp(-x) < u
        low, high = np.where(under, x, low), np.where(under, high, x)
    return (low + high) / 2


_GAMMA = _gamma_table().astype(np.float32)
_LOG_GAMMA, _INVERSE_GAMMA = np.log(_GAMMA), 1 / _GAMMA
_SEEDS = W.mix(np.arange(1, 4097, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def counted_shingles(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, shingle, count) of the texts of a column, sorted by row and shingle."""
    row, hashed = W.shingle_hashes(W.scan(*C.text_bytes(column)), SHINGLE)
    if len(row) == 0:
        return row, hashed, np.zeros(0, np.float32)
    key = (row.astype(np.uint64) << np.uint64(ID_BITS)) | (hashed >> np.uint64(64 - ID_BITS))
    key.sort()
    first = np.concatenate([[True], key[1:] != key[:-1]])
    at = np.flatnonzero(first)
    count = np.diff(np.append(at, len(key))).astype(np.float32)
    key = key[at]
    return (key >> np.uint64(ID_BITS)).astype(np.int64), key & np.uint64((1 << ID_BITS) - 1), count


class Idf:
    """Smoothed inverse document frequencies, given by document counts or by a table of (shingles, their counts)."""

    def __init__(self, documents: int, shingles=(), counts=()):
        self.documents = max(documents, 1)
        order = np.argsort(shingles)
        self.shingles = np.asarray(shingles, dtype=np.uint64)[order]
        self.counts = np.asarray(counts, dtype=np.int64)[order]

    def of(self, held: np.ndarray, count: np.ndarray) -> np.ndarray:
        """Weights of shingles that stand `count` times in a text and that `held` documents hold."""
        whole = np.log(self.documents) or 1.0
        return count * (SMOOTH + np.log(self.documents / np.maximum(held, 1)) / whole).astype(np.float32)

    def weights(self, shingle: np.ndarray, count: np.ndarray) -> np.ndarray:
        """The same by the table; a shingle that is not in it is in one document."""
        held = np.ones(len(shingle), np.int64)
        if len(self.shingles):
            at = np.minimum(np.searchsorted(self.shingles, shingle), len(self.shingles) - 1)
            held = np.where(self.shingles[at] == shingle, self.counts[at], 1)
        return self.of(held, count)


def samples(row: np.ndarray, shingle: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows that have shingles, their SAMPLES samples as hashes) by improved consistent weighted sampling.

    The three random numbers of a shingle and sample are 16-bit fields of one hash; buffers are reused, as
    this loop is the operator's main cost.
    """
    rows, start = np.unique(row, return_index=True)
    if len(rows) == 0:
        return rows, np.zeros((SAMPLES, 0), np.uint64)
    log_weight = np.log(weight)
    n = len(row)
    index, low = np.arange(n, dtype=np.uint64), np.uint64(0xFFFFFFFF)
    h, work = np.empty(n, np.uint64), np.empty(n, np.uint64)
    fields = h.view(np.uint16).reshape(-1, 4)
    sample = np.empty((SAMPLES, len(rows)), dtype=np.uint64)
    for k in range(SAMPLES):
        np.multiply(shingle, _SEEDS[k], out=h)
        np.right_shift(h, np.uint64(29), out=work)
        np.bitwise_xor(h, work, out=h)
        np.multiply(h, _SEEDS[k + SAMPLES], out=h)
        r = fields[:, 3]
        beta = fields[:, 1].astype(np.float32)
        beta *= np.float32(1 / 65536)
        level = log_weight * _INVERSE_GAMMA.take(r)
        level += beta
        np.floor(level, out=level)
        a = level - beta
        a += 1
        a *= _GAMMA.take(r)
        np.subtract(_LOG_GAMMA.take(fields[:, 2]), a, out=a)
        np.exp(a, out=a)
        # positive floats order as their bits do; the place of the smallest rides below them
        work[:] = a.view(np.uint32)
        work <<= np.uint64(32)
        work |= index
        at = (np.minimum.reduceat(work, start) & low).astype(np.int64)
        sample[k] = W.mix(h[at] ^ (level[at].astype(np.int64).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
    return rows, sample


def band_keys(row: np.ndarray, shingle: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(rows that have shingles, their band keys): one key for every ROWS samples."""
    rows, sample = samples(row, shingle, weight)
    keys = np.empty((len(rows), SAMPLES // ROWS), dtype=np.uint64)
    for b in range(SAMPLES // ROWS):
        total = np.full(len(rows), b + 1, dtype=np.uint64)
        for i in range(ROWS):
            total = W.mix(total * np.uint64(0x9E3779B97F4A7C15) + sample[b * ROWS + i])
        keys[:, b] = total
    return rows, keys


def group_sums(row: np.ndarray, shingle: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows that have shingles, rounded sums of their weights by group, their whole weights)."""
    rows, at = np.unique(row, return_inverse=True)
    cell = at * GROUPS + (shingle % np.uint64(GROUPS)).astype(np.int64)
    sums = np.bincount(cell, weight, len(rows) * GROUPS).reshape(len(rows), GROUPS)
    return rows, np.minimum(np.rint(sums * UNIT), MOST).astype(np.int16), sums.sum(axis=1)


def most_unlike(weights, least: float):
    """How much the sums of two texts of together `weights` may differ if the texts are similar enough.

    Similarity t means that weights differ by (1 - t) / (1 + t) of their sum; rounding adds a step a group at most.
    """
    least -= 1e-9
    return weights * ((1 - least) / (1 + least) * UNIT) + (GROUPS + 1)


def similarity(a: tuple, b: tuple) -> float:
    """Weighted Jaccard similarity of two (sorted shingles, weights)."""
    if not len(a[0]) or not len(b[0]):
        return 0.0
    at = np.minimum(np.searchsorted(b[0], a[0]), len(b[0]) - 1)
    same = b[0][at] == a[0]
    least = np.minimum(a[1][same], b[1][at[same]]).sum(dtype=np.float64)
    return float(least / (a[1].sum(dtype=np.float64) + b[1].sum(dtype=np.float64) - least))


def _steps(key: np.ndarray) -> bytes:
    """Ascending keys (one at least): the first, and the steps between them, in four bytes each where these do."""
    step = np.diff(key)
    small = not len(step) or step.max() >> np.uint64(32) == 0
    return (b"4" if small else b"8") + key[:1].tobytes() + step.astype(np.uint32 if small else np.uint64).tobytes()


def _keys(steps: bytes) -> np.ndarray:
    step = np.frombuffer(steps, np.uint32 if steps[:1] == b"4" else np.uint64, offset=9)
    return np.cumsum(np.concatenate([np.frombuffer(steps, np.uint64, 1, 1), step]), dtype=np.uint64)


def _packed(parts) -> pa.Array:
    return pa.array([p.tobytes() if isinstance(p, np.ndarray) else p for p in parts], pa.binary())


def _squeezed(texts: pa.Array) -> tuple[np.ndarray, bytes]:
    """(lengths in bytes, all texts as one compressed string): blocks are written once and shuffled once."""
    raw, offsets = C.text_bytes(texts)
    return np.diff(offsets), pa.Codec("zstd", ZSTD).compress(np.ascontiguousarray(raw), asbytes=True)


def _texts(block: pa.RecordBatch, i: int) -> pa.Array:
    """The texts of a block, the i-th row."""
    length = block.column("length").slice(i, 1).flatten().to_numpy()
    offsets = np.concatenate([[0], np.cumsum(length)]).astype(np.int64)
    raw = pa.Codec("zstd").decompress(block.column("text")[i].as_buffer(), int(offsets[-1])) if offsets[-1] else pa.py_buffer(b"")
    return pa.LargeStringArray.from_buffers(len(length), pa.py_buffer(offsets), raw)


def blocks(named: DataFrame) -> DataFrame:
    """block, node, own, length (three lists), text (all, compressed) of named(node, own, text): about BLOCK bytes of text to a row."""

    def run(batches):
        from pyspark import TaskContext

        at, held, size = TaskContext.get().partitionId() << 33, [], 0

        def flush():
            whole = pa.Table.from_batches(held).combine_chunks()
            length, text = _squeezed(whole.column("text").combine_chunks())
            lists = [pa.ListArray.from_arrays(pa.array([0, whole.num_rows], pa.int32()), c) for c in (whole.column("node").combine_chunks(), whole.column("own").combine_chunks(), pa.array(length, pa.int64()))]
            return pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), *lists, pa.array([text], pa.binary())], names=["block", "node", "own", "length", "text"])

        for b in batches:
            for piece in C.small_batches(b, "text", BATCH):
                held.append(piece)
                size += piece.column("text").nbytes
                if size >= BLOCK:
                    yield flush()
                    at, held, size = at + 1, [], 0
        if held:
            yield flush()

    return named.select("node", "own", "text").mapInArrow(run, "block long, node array<long>, own array<boolean>, length array<long>, text binary")


def _block_shingles(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """counted_shingles of all texts of a block, a piece of them at a time."""
    found, first = [], 0
    for piece in C.small_batches(pa.RecordBatch.from_arrays([texts], names=["text"]), "text", BATCH):
        row, shingle, count = counted_shingles(piece.column("text"))
        found.append((row + first, shingle, count))
        first += piece.num_rows
    return tuple(np.concatenate(c) for c in zip(*found))


def document_frequencies(dealt: DataFrame, ranges: int) -> DataFrame:
    """block, part, held: how many documents hold each distinct shingle of a block, in ascending order through its parts.

    dealt: the table of blocks. Part p holds the shingles of the p-th of equal ranges of hashes.
    """
    edges = np.array([(p << ID_BITS) // ranges for p in range(1, ranges)], dtype=np.uint64)

    def ask(batches):
        for b in batches:
            for i in range(b.num_rows):
                key, n = np.unique(_block_shingles(_texts(b, i))[1], return_counts=True)
                cut = np.concatenate([[0], np.searchsorted(key, edges), [len(key)]])
                part = np.flatnonzero(np.diff(cut))
                own = pa.array(np.full(len(part), b.column("block")[i].as_py(), np.int64))
                runs = [(_steps(key[cut[p] : cut[p + 1]]), n[cut[p] : cut[p + 1]].astype(np.uint32)) for p in part]
                yield pa.RecordBatch.from_arrays([pa.array(part.astype(np.int32)), own, _packed(k for k, _ in runs), _packed(c for _, c in runs)], names=["part", "block", "steps", "n"])

    def answer(batches):
        part, asked = None, []

        def flush():
            key = [_keys(k) for _, k, _ in asked]
            at = np.unique(np.concatenate(key), return_inverse=True)[1]
            n = np.concatenate([np.frombuffer(c, np.uint32) for _, _, c in asked])
            held = np.bincount(at, n)[at].astype(np.uint32)
            cut = np.cumsum([0, *map(len, key)])
            return pa.RecordBatch.from_arrays(
                [pa.array([block for block, _, _ in asked], pa.int64()), pa.array(np.full(len(asked), part, np.int32)), _packed(held[cut[i] : cut[i + 1]] for i in range(len(asked)))], names=["block", "part", "held"])

        for b in batches:
            for p, *run in zip(*(b.column(c).to_pylist() for c in ("part", "block", "steps", "n"))):
                if p != part and asked:
                    yield flush()
                    asked = []
                part = p
                asked.append(run)
        if asked:
            yield flush()

    runs = dealt.select("block", "length", "text").mapInArrow(ask, "part int, block long, steps binary, n binary")
    return runs.repartition(ranges, "part").sortWithinPartitions("part").mapInArrow(answer, "block long, part int, held binary")


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))


def signatures(dealt: DataFrame, answers: DataFrame, idf: Idf, tasks: int) -> DataFrame:
    """node, bands, held (the document counts of its shingles, in their order) of every own row of the blocks that has a word."""
    none = [F.lit(None).cast(t).alias(c) for c, t in (("node", "array<long>"), ("own", "array<boolean>"), ("length", "array<long>"), ("text", "binary"))]
    texts = dealt.select("block", F.lit(-1).alias("part"), "node", "own", "length", "text", F.lit(None).cast("binary").alias("held"))
    met = texts.unionByName(answers.select("block", "part", *none, "held")).repartition(tasks, "block").sortWithinPartitions("block", "part")

    def signed(node, own, text, held):
        row, shingle, count = _block_shingles(text)
        key, at = np.unique(shingle, return_inverse=True)
        held = np.frombuffer(b"".join(held), np.uint32)
        if len(held) != len(key):
            raise ValueError(f"{len(held)} answers to {len(key)} shingles of a block")
        wanted = own.to_numpy(zero_copy_only=False)[row]
        row, shingle, count, held = row[wanted], shingle[wanted], count[wanted], held[at][wanted]
        for first in range(0, len(text), 64):  # the kernel's buffers stay in the cache
            a, z = np.searchsorted(row, (first, first + 64))
            rows, keys = band_keys(row[a:z], shingle[a:z], idf.of(held[a:z], count[a:z]))
            cut = np.searchsorted(row, rows), np.searchsorted(row, rows, side="right")
            yield pa.RecordBatch.from_arrays([node.take(pa.array(rows)), _lists(keys.astype(np.int64)), _packed(held[x:y] for x, y in zip(*cut))], names=["node", "bands", "held"])

    def run(batches):
        own, held = None, []
        for b in batches:
            part = b.column("part").to_numpy()
            for i in range(b.num_rows):
                if part[i] < 0:
                    if own:
                        yield from signed(*own, held)
                    own, held = (*(b.column(c).slice(i, 1).flatten() for c in ("node", "own")), _texts(b, i)), []
                else:
                    held.append(b.column("held")[i].as_py())
        if own:
            yield from signed(*own, held)

    return met.mapInArrow(run, "node long, bands array<long>, held binary")


def signed_blocks(named: DataFrame, idf: Idf) -> DataFrame:
    """The signatures of named(node, own, text), written. Block rows are large, so few of them are read or cross to Python at once meanwhile."""
    spark, names = named.sparkSession, ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.parquet.columnarReaderBatchSize")
    dealt = C.materialize(blocks(named), "near-blocks", LARGE_ROWS)
    n = dealt.count()
    before = [spark.conf.get(name) for name in names]
    for name in names:
        spark.conf.set(name, str(BLOCK_ROWS))
    try:
        answers = C.materialize(document_frequencies(dealt, max(1, n * BLOCK // 8 // RANGE)), "near-frequencies")
        return C.materialize(signatures(dealt, answers, idf, max(1, n // BLOCK_TASK)), "near-signatures")
    finally:
        for name, value in zip(names, before):
            spark.conf.set(name, value)


def _weighed(piece: pa.RecordBatch, idf: Idf) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, shingle, weight) of rows with a text and the document counts of its shingles."""
    row, shingle, count = counted_shingles(piece.column("text"))
    return row, shingle, idf.of(np.frombuffer(b"".join(piece.column("held").to_pylist()), np.uint32), count)


def grouped(nodes: DataFrame, idf: Idf) -> DataFrame:
    """node, sums, weight of every row of nodes(node, text, held) that has a word."""

    def run(batches):
        for b in batches:
            for piece in C.small_batches(b, "text", BATCH):
                rows, sums, weight = group_sums(*_weighed(piece, idf))
                yield pa.RecordBatch.from_arrays([piece.column("node").take(pa.array(rows)), _lists(sums), pa.array(weight)], names=["node", "sums", "weight"])

    return nodes.select("node", "text", "held").mapInArrow(run, "node long, sums array<smallint>, weight double")


def verify(pairs: DataFrame, texts: DataFrame, idf: Idf, least: float = SIMILAR, together: int = 256) -> DataFrame:
    """a, b of the pairs(pivot, node) whose texts(node, text, held) are similar enough.

    A pivot's text goes once to each group of about `together` of its partners, so neither a popular
    pivot nor its text's length meets a single task; a task holds one pivot at a time.
    """
    sizes = pairs.groupBy("pivot").agg(F.ceil(F.count("*") / together).cast("int").alias("groups"))
    # a text is joined once for all the groups that its node is needed in
    asked = (
        pairs.join(sizes, "pivot").select("node", F.struct("pivot", F.pmod(F.xxhash64("node"), F.col("groups")).cast("int").alias("part")).alias("to"))
        .groupBy("node").agg(F.collect_list("to").alias("to"))
    )
    members = asked.join(texts, "node").select(F.explode("to").alias("to"), F.lit(1).alias("role"), "node", "text", "held").select("to.pivot", "to.part", "role", "node", "text", "held")
    pivots = (
        sizes.join(texts.withColumnRenamed("node", "pivot"), "pivot")
        .select("pivot", F.explode(F.sequence(F.lit(0), F.col("groups") - 1)).alias("part"), F.lit(0).alias("role"), F.col("pivot").alias("node"), "text", "held")
    )
    dealt = pivots.unionByName(members).repartition("pivot", "part").sortWithinPartitions("pivot", "part", "role")

    def run(batches):
        key, own = None, None
        for b in batches:
            for piece in C.small_batches(b, "text", BATCH):
                row, shingle, weight = _weighed(piece, idf)
                cut = np.searchsorted(row, np.arange(piece.num_rows + 1))
                pivot, part, role, node = (piece.column(c).to_pylist() for c in ("pivot", "part", "role", "node"))
                a, n = [], []
                for i in range(piece.num_rows):
                    vector = shingle[cut[i] : cut[i + 1]], weight[cut[i] : cut[i + 1]]
                    if role[i] == 0:
                        key, own = (pivot[i], part[i]), vector
                    elif key == (pivot[i], part[i]) and similarity(own, vector) >= least - 1e-9:
                        a.append(pivot[i])
                        n.append(node[i])
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(n, pa.int64())], names=["a", "b"])

    return dealt.mapInArrow(run, C.schema(a=C.LONG, b=C.LONG))


def components(edges: DataFrame) -> DataFrame:
    """node, root of every node of edges(a, b): alternating stars, each round a few shuffles; root is the smallest node."""
    low, high = F.least("a", "b"), F.greatest("a", "b")
    stars = C.materialize(edges.select(high.alias("u"), low.alias("v")).where("u != v").distinct(), "near-edges")
    seen = None
    while True:
        mark = stars.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            return stars.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(stars.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
        seen = mark
        both = stars.unionByName(stars.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        stars = C.materialize(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "near-stars")


def _texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """node, text of the wanted(node, doc_id), read from docs in one scan; broadcast only below a checked size."""
    rows = docs.select("doc_id", "text", F.xxhash64("text").alias("node"))
    wanted = _small(C.materialize(wanted, "near-wanted"))
    return C.materialize(rows.join(wanted, ["doc_id", "node"]).select("node", "text"), "near-texts").dropDuplicates(["node"])


def link(docs: DataFrame, nodes: DataFrame, named: DataFrame, documents: int, least: float = SIMILAR) -> DataFrame:
    """node, root of all nodes that are linked to another. named(node, own, text): all documents; the own rows, those of nodes(node, doc_id), are signed."""
    idf = Idf(documents)
    signed = signed_blocks(named, idf)
    slots = C.materialize(signed.select("node", F.explode("bands").alias("key")).distinct(), "near-slots")  # a row may stand in the table twice
    buckets = slots.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    members = C.materialize(slots.join(buckets, "key").select("key", "n", "node"), "near-members")
    met = members.withColumn("met", F.sum("n").over(Window.partitionBy("node")))  # a node has one row a band at most
    pivots = met.groupBy("key").agg(F.max_by("node", F.struct("met", "node")).alias("pivot"))
    pairs = C.materialize(members.join(pivots, "key").where("node != pivot").select("pivot", "node").distinct(), "near-pairs")
    texts = _texts_of(docs, members.select("node").distinct().join(nodes, "node").select("node", "doc_id"))
    texts = C.materialize(texts.join(signed.select("node", "held"), "node").dropDuplicates(["node"]), "near-vectors")
    edges = C.materialize(verify(pairs, texts, idf, least), "near-links")
    roots = components(edges)

    # buckets of three and more may hold further links, between members that the pivot is not like
    placed = members.where("n > 2").select("key", "node").join(roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root"))
    split = placed.groupBy("key", "root").agg(F.count("*").alias("n")).groupBy("key").agg(F.max_by("root", F.struct("n", "root")).alias("main"), F.count("*").alias("roots")).where("roots > 1")
    placed = C.materialize(placed.join(split.select("key", "main"), "key"), "near-split")
    if placed.isEmpty():
        return roots
    wanted = placed.select("node").distinct()
    known = signed.select("node", "bands").join(wanted, "node").dropDuplicates(["node"]).join(grouped(texts.join(wanted, "node"), idf), "node")
    placed = C.materialize(placed.join(known, "node").select("key", "node", "root", "main", "bands", "sums", "weight"), "near-split-signed")
    own = placed.where("root != main").select(F.col("key").alias("own_key"), F.col("node").alias("pivot"), F.col("root").alias("own"), F.col("bands").alias("own_bands"), F.col("sums").alias("own_sums"), F.col("weight").alias("own_weight"))
    unlike = F.aggregate(F.zip_with("sums", "own_sums", lambda x, y: F.abs(x - y)), F.lit(0), lambda total, x: total + x)
    close = unlike <= most_unlike(F.col("weight") + F.col("own_weight"), least)
    once = F.array_min(F.array_intersect("bands", "own_bands")) == F.col("key")
    # two outsiders of one bucket meet from either side: the one of the smaller id asks
    ordered = (F.col("root") == F.col("main")) | (F.col("pivot") < F.col("node"))
    other = placed.join(own, (F.col("key") == F.col("own_key")) & (F.col("root") != F.col("own")) & ordered & once & close).select("pivot", "node")
    pair = (F.least("pivot", "node").alias("pivot"), F.greatest("pivot", "node").alias("node"))
    fresh = C.materialize(other.select(*pair).distinct().join(pairs.select(*pair), ["pivot", "node"], "left_anti"), "near-pairs")
    more = C.materialize(verify(fresh, texts, idf, least), "near-links")
    return roots if more.isEmpty() else components(edges.unionByName(more))


def _small(df: DataFrame) -> DataFrame:
    """A materialized table, broadcast only below a checked size."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def found_classes(docs: DataFrame, least: float = SIMILAR) -> DataFrame:
    """doc_id, node, class_id, first_node, class_size of every row of docs; the row (class_id, first_node) stands for its class."""
    keys = C.materialize(docs.select("doc_id", F.when(F.col("text").isNotNull(), F.xxhash64("text")).alias("node")), "near-keys")
    known = keys.where("doc_id is not null and node is not null")
    nodes = C.materialize(known.groupBy("node").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("rows")), "near-nodes")
    documents = keys.where("node is not null").count()
    # every document counts for frequencies; of equal texts only the first is signed: the others' keys (doc_id, node) are many, but no key is hot
    copies = nodes.where("rows > 1").select("node", F.col("doc_id").alias("first_id"))
    later = C.materialize(known.join(_small(C.materialize(copies, "near-copies")), "node").where("doc_id != first_id").select("doc_id", "node").distinct(), "near-later")
    named = docs.select("doc_id", "text", F.xxhash64("text").alias("node")).where("doc_id is not null and text is not null")
    named = named.join(_small(later).withColumn("again", F.lit(True)), ["doc_id", "node"], "left").select("node", F.col("again").isNull().alias("own"), "text")
    roots = C.materialize(link(docs.select("doc_id", "text").where("doc_id is not null"), nodes, named, documents, least), "near-roots")
    placed = nodes.join(roots, "node", "left").select("node", "doc_id", "rows", F.coalesce("root", "node").alias("root"))
    groups = placed.groupBy("root").agg(F.min(F.struct("doc_id", "node")).alias("first"), F.sum("rows").alias("class_size"))
    # only nodes with company need a look-up
    by_node = placed.join(groups, "root").where("class_size > 1").select("node", F.col("first.doc_id").alias("class_id"), F.col("first.node").alias("first_node"), "class_size")
    return keys.join(_small(C.materialize(by_node, "near-classes")), "node", "left").select(
        "doc_id", "node", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("first_node", "node").alias("first_node"), F.coalesce("class_size", F.lit(1)).cast("long").alias("class_size"))


def classes(docs: DataFrame, least: float = SIMILAR) -> DataFrame:
    """doc_id, class_id (the smallest doc_id of the class), class_size of every row of docs."""
    return found_classes(docs, least).select("doc_id", "class_id", "class_size")


def keep_one(docs: DataFrame, least: float = SIMILAR) -> DataFrame:
    """docs with one row of each class: of the rows with the smallest doc_id one stays (the smallest hash of its text).

    Rows go by doc_id and text, so a doc_id that stands for several texts loses only those that have a class mate. Rows
    without doc_id or text stay as they are; so do all columns.
    """
    found = C.materialize(found_classes(docs, least).where("doc_id is not null and node is not null"), "near-found")
    gone = C.materialize(found.where("doc_id != class_id or node != first_node").select("doc_id", "node").distinct(), "near-gone")
    twice = C.materialize(found.where("doc_id = class_id and node = first_node and class_size > 1").groupBy("doc_id", "node").count().where("count > 1").select("doc_id", "node"), "near-twice")
    own = lambda df: df.select(F.col("doc_id").alias("near_doc_id__"), F.col("node").alias("near_node__"))
    same = (F.xxhash64(docs["text"]) == F.col("near_node__")) & (docs["doc_id"] == F.col("near_doc_id__")) & docs["text"].isNotNull()
    kept = docs.join(own(_small(gone)), same, "left_anti")
    if twice.isEmpty():
        return kept
    again = own(_small(twice))
    return kept.join(again, same, "left_anti").unionByName(kept.join(again, same, "left_semi").dropDuplicates(["doc_id", "text"]))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(C.table(spark, sf_dir, "documents"))
