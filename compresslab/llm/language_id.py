"""Language identification by compression: the language whose dictionary makes a text smallest.

For every language of the training rows a raw-content zstandard dictionary is built. Training texts are cut, whole, into
pieces of PIECE characters; about `sample` pieces of each language, chosen by a hash, are its dictionary, for the `languages`
most frequent languages. These two numbers bound the fit. A whole text, folded to lower case with runs of other characters
as one blank, is compressed piece by piece with each dictionary; the smallest sum of sizes wins. Sizes are whole bytes, so
short texts may tie: then each of the text's suffixes that starts at a word is compressed as well and the smallest sum of
these sizes wins, then the language that sorts first. The margin is the relative distance to the second; `rejected` marks a
margin below min_margin.

Null texts and texts without a letter are `und` with score 0, as is every text if nothing was learned. Rows with a null lang,
text or doc_id are never learned from; a doc_id that is repeated is learned from like any other row. Null doc_ids are judged
and held_out is null for them. Repeated rows are judged alike. An empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C
from . import words as W

PIECE, LEVEL = 1024, 6


def learn(docs: DataFrame, sample: int = 256, languages: int = 200) -> dict[str, bytes]:
    """Dictionaries by language, of about `sample` pieces each (all, if there are fewer), chosen among the pieces of whole texts."""
    held = docs.select("doc_id", "text", "lang").where("doc_id is not null and lang is not null and text is not null").where(F.crc32(F.col("doc_id").cast("string")) % 3 != 1)
    at = F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(F.length("text") / PIECE).cast("int") - 1))).alias("at")
    pieces = held.select("doc_id", "lang", "text", at).select("lang", "doc_id", "at", F.substring(F.col("text"), F.col("at") * PIECE + 1, F.lit(PIECE)).alias("text"))
    count = held.groupBy("lang").agg(F.sum(F.greatest(F.lit(1), F.ceil(F.length("text") / PIECE))).alias("n"))
    sizes = {r["lang"]: r["n"] for r in count.orderBy(F.desc("n"), "lang").limit(languages).collect()}
    keep = F.lit(False)
    for lang, n in sorted(sizes.items()):
        keep = keep | ((F.col("lang") == lang) & (C.hash_unit("doc_id", "at", seed=7) < F.lit(min(1.0, sample / n))))
    rows = pieces.where(keep).select("lang", "text", F.xxhash64("doc_id", "at").alias("at")).dropDuplicates(["lang", "text"]).collect()
    by: dict[str, list[bytes]] = {}
    for r in sorted(rows, key=lambda r: (r["lang"], r["at"], r["text"])):
        by.setdefault(r["lang"], []).append(_folded([r["text"]])[0])
    return {k: b"".join(v) for k, v in sorted(by.items())}


def _folded(texts: list[str]) -> list[bytes]:
    raw, offsets = C.text_bytes(pa.array(texts, pa.large_string()))
    seq, bounds = W.spaced(raw, offsets)
    data = seq.tobytes()
    return [data[bounds[i] : bounds[i + 1]] for i in range(len(texts))]


class Judge:
    def __init__(self, dictionaries: dict[str, bytes], piece: int = PIECE):
        import zstandard

        self.names, self.piece, self.tools = sorted(dictionaries), piece, []
        for name in self.names:
            d = zstandard.ZstdCompressionDict(dictionaries[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=LEVEL)
            self.tools.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False))

    def sizes(self, data: bytes) -> list[int]:
        pieces = [data[i : i + self.piece] for i in range(0, len(data), self.piece)]
        return [sum(len(tool.compress(p)) for p in pieces) for tool in self.tools]

    def suffix_sizes(self, data: bytes, tied) -> dict[int, int]:
        """Sums of the sizes of all suffixes that start at a word: finer than one size. Only short texts tie."""
        starts = [0, *(i for i in range(1, len(data)) if data[i - 1] == 32)]
        return {i: sum(len(self.tools[i].compress(data[at : at + self.piece])) for at in starts) for i in tied}

    def predict(self, column: pa.Array, min_margin: float):
        """Lists lang_pred, score, rejected."""
        lettered = pc.fill_null(pc.match_substring_regex(column, r"\pL"), False).to_pylist()
        folded = _folded(column.to_pylist())
        lang, score, rejected = [], [], []
        for ok, data in zip(lettered, folded):
            if not ok or not self.names:
                lang.append("und")
                score.append(0.0)
                rejected.append(True)
                continue
            sizes = self.sizes(data)
            order = np.argsort(sizes, kind="stable")
            tied = [i for i in order if sizes[i] == sizes[order[0]]]
            if len(tied) > 1:
                finer = self.suffix_sizes(data, tied)
                order = [*sorted(tied, key=lambda i: (finer[i], i)), *order[len(tied) :]]
            best = sizes[order[0]]
            second = sizes[order[1]] if len(order) > 1 else 2 * best + 1
            lang.append(self.names[order[0]])
            score.append(second / (best + second) if best + second else 0.5)
            rejected.append((second - best) < min_margin * second)
        return lang, score, rejected


def predict(docs: DataFrame, dictionaries: dict[str, bytes], min_margin: float = 0.01) -> DataFrame:
    """doc_id, lang_pred, score, rejected of every row; one narrow pass over doc_id and text."""
    shared = docs.sparkSession.sparkContext.broadcast(dictionaries)

    def run(batches):
        judge = Judge(shared.value)
        for b in batches:
            for piece in C.small_batches(b, "text"):
                found = judge.predict(piece.column("text").cast(pa.large_string()), min_margin)
                yield pa.RecordBatch.from_arrays([piece.column("doc_id").cast(pa.int64()), *(pa.array(x, t) for x, t in zip(found, (pa.string(), pa.float64(), pa.bool_())))], names=["doc_id", "lang_pred", "score", "rejected"])

    return docs.select("doc_id", "text").mapInArrow(run, C.schema(doc_id=C.LONG, lang_pred=C.STRING, score=C.DOUBLE, rejected=C.BOOLEAN))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    found = predict(docs, learn(docs))
    return found.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 3 == 1).alias("held_out"), "lang_pred", "score", "rejected")
