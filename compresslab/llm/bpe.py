"""Byte-level BPE by overlapping chunks: pre-tokenise chunks, stitch them, encode the pieces, decode.

Every text is cut into chunks that overlap (a text of up to one chunk is a single one). Every chunk is pre-tokenised by
itself, starting at its own first character, so its first boundaries may be wrong; but the pattern scans from left to
right and looks ahead by one character only, so from the first boundary that it shares with the chunk before it, both
scans agree for ever. The stitch takes the earlier chunk's boundaries up to that place and the later chunk's from there
on. A match that reaches into the last characters of a chunk is not trusted, as the chunk's end may have cut it. Where an
overlap holds no shared boundary (one match longer than the overlap), the scan goes on from the last trusted boundary
over twice the room. The pieces between boundaries are then encoded one by one.

Texts of up to spread_chars characters are chunked inside one task. Longer ones become chunk rows that all executors
pre-tokenise in parallel. Their chunks are then put together per document, text and boundaries, in one task: a document's
hash of ids needs all of them in order, so a task must hold the longest document.

Null and empty texts give no ids (n_tokens 0, hashes of nothing). Repeated rows are encoded each. An empty table gives no
rows. Extra columns are not read.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common as C

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
CHUNK, OVERLAP, SPREAD = 1 << 12, 1 << 8, 1 << 22


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def default_vocabulary() -> tuple[dict[bytes, int], str]:
    import public_tokenizers

    return load_ranks(public_tokenizers.path(VOCABULARY)), public_tokenizers.PATTERN


def chunk_ends(text: str, start: int, stop: int, pattern) -> list[int]:
    """Ends of the matches of pattern in text[start:stop], scanned as if the text began and ended there."""
    return [m.end() for m in pattern.finditer(text, start, stop)]


def stitch(before: list[int], after: list[int], trusted: int) -> tuple[list[int], bool]:
    """Join two sorted boundary lists at their first shared boundary not beyond `trusted`; False if there is none."""
    import bisect

    i, known = 0, set(after)
    i = bisect.bisect_left(before, after[0]) if after else len(before)
    while i < len(before) and before[i] <= trusted:
        if before[i] in known:
            return before[:i] + after[bisect.bisect_left(after, before[i]) :], True
        i += 1
    return before[: bisect.bisect_right(before, trusted)], False


def boundaries(text: str, pattern, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[int]:
    """Ends of all pre-tokens of a text, from overlapping chunks."""
    n = len(text)
    ends = chunk_ends(text, 0, min(n, chunk + overlap), pattern)
    reached = min(n, chunk + overlap)
    begin = chunk
    while reached < n:
        stop = min(n, begin + chunk + overlap)
        after = chunk_ends(text, begin, stop, pattern)
        joined, ok = stitch(ends, after, reached - 2)
        if ok:
            ends, reached, begin = joined, stop, begin + chunk
        else:
            room = chunk + overlap
            last = joined[-1] if joined else 0
            while True:
                stop = min(n, last + 2 * room)
                more = chunk_ends(text, last, stop, pattern)
                if stop == n or (more and more[0] <= stop - 2):
                    break
                room *= 2
            ends, reached = joined + more, stop
            begin = max(last + 1, stop - overlap)
    return ends


class Codec:
    """Encoder and decoder of one vocabulary; pieces met before come from a bounded memory."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, remember: int = 50_000):
        import regex
        import tiktoken

        self.pattern = regex.compile(pattern)
        # the library merges the bytes of one piece; its own pattern takes whatever it is given as one match
        self.merges = tiktoken.Encoding("pieces", pat_str=r"(?s:.+)", mergeable_ranks=ranks, special_tokens={})
        self.bytes_of = {v: k for k, v in ranks.items()}
        self.seen: dict[str, list[int]] = {}
        self.remember = remember

    def piece(self, piece: str) -> list[int]:
        ids = self.seen.get(piece)
        if ids is None:
            ids = self.merges.encode_ordinary(piece)
            if len(self.seen) < self.remember and len(piece) <= 32:
                self.seen[piece] = ids
        return ids

    def encode(self, text: str, chunk: int = CHUNK, overlap: int = OVERLAP) -> list[int]:
        return self.encode_at(text, boundaries(text, self.pattern, chunk, overlap))

    def encode_at(self, text: str, ends: list[int]) -> list[int]:
        ids, start, seen = [], 0, self.seen
        for end in ends:
            piece = text[start:end]
            ids += seen.get(piece) or self.piece(piece)
            start = end
        return ids

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


_codecs: dict[int, Codec] = {}


def _codec(shared) -> Codec:
    """One codec for each worker process and vocabulary."""
    ranks, pattern = shared.value
    if id(ranks) not in _codecs:
        _codecs.clear()
        _codecs[id(ranks)] = Codec(ranks, pattern)
    return _codecs[id(ranks)]


_IDS = pa.list_(pa.int32())


def _encode_rows(shared, chunk, overlap, keep_ids):
    def run(batches):
        codec = _codec(shared)
        for batch in batches:
            for piece in C.small_batches(batch, "text", 1 << 20):
                found = [codec.encode(t or "", chunk, overlap) for t in piece.column("text").to_pylist()]
                yield _result(piece.column("doc_id").cast(pa.int64()), found, codec, keep_ids)

    return run


def _result(doc_id, found, codec, keep_ids) -> pa.RecordBatch:
    digest = [hashlib.sha256(np.asarray(ids, dtype="<u4").tobytes()).hexdigest() for ids in found]
    back = [hashlib.sha256(codec.decode(ids)).hexdigest() for ids in found]
    columns = {"doc_id": doc_id, "n_tokens": pa.array([len(x) for x in found], pa.int64()), "ids_sha256": pa.array(digest), "decoded_sha256": pa.array(back)}
    if keep_ids:
        columns["ids"] = pa.array(found, _IDS)
    return pa.RecordBatch.from_pydict(columns)


def encode(docs: DataFrame, ranks: dict[bytes, int] | None = None, pattern: str | None = None, keep_ids: bool = False, chunk: int = CHUNK, overlap: int = OVERLAP, spread_chars: int = SPREAD) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, if wanted) of every row of docs."""
    spark = docs.sparkSession
    if ranks is None:
        ranks, pattern = default_vocabulary()
    shared = spark.sparkContext.broadcast((ranks, pattern))
    out = C.schema(doc_id=C.LONG, n_tokens=C.LONG, ids_sha256=C.STRING, decoded_sha256=C.STRING)
    if keep_ids:
        out = out.add("ids", T.ArrayType(T.IntegerType()))
    rows = docs.select("doc_id", "text")
    long_text = F.coalesce(F.length("text"), F.lit(0)) > spread_chars
    short = rows.where(~long_text).mapInArrow(_encode_rows(shared, chunk, overlap, keep_ids), out)

    # very long texts: chunk rows in all tasks, each with the boundaries that it finds
    room = max(chunk, spread_chars // 8)
    spread = (
        rows.where(long_text)
        .select("doc_id", F.monotonically_increasing_id().alias("at"), "text", F.length("text").alias("n"))
        .select("doc_id", "at", "n", "text", F.explode(F.sequence(F.lit(0), ((F.col("n") - 1) / room).cast("int"))).alias("k"))
        .select("doc_id", "at", "n", "k", F.substring(F.col("text"), F.col("k") * room + 1, F.lit(room + overlap)).alias("text"))
        .repartition(F.col("at"), F.col("k"))
    )

    def find(batches):
        codec = _codec(shared)
        for b in batches:
            for piece in C.small_batches(b, "text", 1 << 20):
                ends = [[k * room + e for e in chunk_ends(t, 0, len(t), codec.pattern)] for t, k in zip(piece.column("text").to_pylist(), piece.column("k").to_pylist())]
                yield pa.RecordBatch.from_pydict({"doc_id": piece.column("doc_id"), "at": piece.column("at"), "n": piece.column("n"), "k": piece.column("k"), "text": piece.column("text"), "ends": pa.array(ends, pa.list_(pa.int64()))})

    chunks = spread.mapInArrow(find, "doc_id long, at long, n int, k int, text string, ends array<long>")
    whole = chunks.groupBy("at").agg(F.first("doc_id").alias("doc_id"), F.sort_array(F.collect_list(F.struct("k", "text", "ends"))).alias("parts"))

    def join(batches):
        codec = _codec(shared)
        for b in batches:
            for i in range(b.num_rows):
                parts = b.column("parts")[i].as_py()
                text = "".join(p["text"][:room] for p in parts[:-1]) + parts[-1]["text"]
                ends, ok = parts[0]["ends"], True
                for before, after in zip(parts, parts[1:]):
                    ends, ok = stitch(ends, after["ends"], before["k"] * room + len(before["text"]) - 2)
                    if not ok:
                        break
                found = codec.encode_at(text, ends if ok else boundaries(text, codec.pattern, room, overlap))
                yield _result(b.column("doc_id").slice(i, 1), [found], codec, keep_ids)

    return short.unionByName(whole.select("doc_id", "parts").mapInArrow(join, out))


def decode(encoded: DataFrame, ranks: dict[bytes, int] | None = None) -> DataFrame:
    """doc_id and text bytes of rows with ids."""
    spark = encoded.sparkSession
    shared = spark.sparkContext.broadcast(ranks or default_vocabulary()[0])

    def run(batches):
        names = {v: k for k, v in shared.value.items()}
        for b in batches:
            texts = [b"".join(names[i] for i in ids or []) for ids in b.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(texts, pa.binary())], names=["doc_id", "raw"])

    return encoded.select("doc_id", "ids").mapInArrow(run, C.schema(doc_id=C.LONG, raw=C.BINARY))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(C.table(spark, sf_dir, "documents"))
