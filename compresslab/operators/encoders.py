"""Deterministic text encoders with the contract of embedding models: text in, a fixed number of floats out.

Tokens are hashed (first 8 hex digits of md5) to a slot and a sign, and their counts summed by slot; a text stands in
one row, so encoding is narrow. Variants stand for models of different dimension and training:
weights that fall with the position make prefixes carry most of a vector, an offset moves every coordinate off zero,
and odd powers give heavy tails.
"""

from __future__ import annotations

import hashlib
import json
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import tokens as T
from ..functions import vectors as V
from .codecs import Codec, hash_signs

_LETTERS = regex.compile(r"\p{L}+")


@dataclass(frozen=True)
class HashedEncoder:
    name: str
    dims: int
    unit: str  # word or gram
    decay: float = 0.0  # weight of slot j is 1 / (1 + decay * j)
    break_at: int = 0  # slots from here on weigh a quarter
    offset: float = 0.0
    cubed: bool = False

    @property
    def nested(self) -> bool:
        return bool(self.decay or self.break_at)


# stand-ins for the four models: two of 1024 and two of 768 dimensions, one of each with useful prefixes
ENCODERS = (
    HashedEncoder("hash1024_ordered", 1024, "word", decay=1 / 128),
    HashedEncoder("hash1024_offset", 1024, "word", offset=0.75),
    HashedEncoder("gram768_ordered", 768, "gram", break_at=256),
    HashedEncoder("gram768_plain", 768, "gram", cubed=True),
)


def tokens(text: str, unit: str) -> list[str]:
    """Words (runs of letters) or runs of three characters, in lower case."""
    low = text.lower()
    return _LETTERS.findall(low) if unit == "word" else [low[i : i + 3] for i in range(len(low) - 2)]


_memory: dict[str | int, int] = {}  # digests of tokens met before, bounded, one for each process


def _digest(token: str | int) -> int:
    h = _memory.get(token)
    if h is None:
        h = int(hashlib.md5((token if isinstance(token, str) else T.gram_text(token)).encode()).hexdigest()[:8], 16)
        if len(_memory) < 500_000:
            _memory[token] = h
    return h


def _places(column: pa.Array, dims: int, unit: str) -> tuple[np.ndarray, np.ndarray]:
    """(cell = row * dims + slot, sign) of every token of a column; only distinct tokens are hashed."""
    row, token = T.words(column) if unit == "word" else T.grams(column)
    coded = (token if unit == "word" else pa.array(token)).dictionary_encode()
    h = T.digests(coded.dictionary) if unit == "word" else np.array([_digest(t) for t in coded.dictionary.to_pylist()], dtype=np.int64)
    at = coded.indices.to_numpy(zero_copy_only=False)
    return row * dims + (h % dims)[at], np.where(h // dims % 2 == 0, 1.0, -1.0)[at]


def counts(column: pa.Array, dims: int, unit: str) -> np.ndarray:
    """Signed counts of the tokens of a text by slot, a row for each text."""
    x = np.zeros((len(column), dims))
    for at, piece in T.pieces(column):
        cell, sign = _places(piece, dims, unit)
        x[at : at + len(piece)] = np.bincount(cell, sign, len(piece) * dims).reshape(len(piece), dims)
    return x


def finish(encoder: HashedEncoder, x: np.ndarray, pos: np.ndarray | slice = slice(None)) -> np.ndarray:
    """Vectors of signed counts; pos: the dimensions that x stands for."""
    weight = 1 / (1 + encoder.decay * np.arange(encoder.dims))
    if encoder.break_at:
        weight[encoder.break_at :] = 0.25
    return (x * np.abs(x) if encoder.cubed else x) * weight[pos] + encoder.offset


def sparse(items: DataFrame, encoder: HashedEncoder, id_col: str = "item_id") -> DataFrame:
    """id, slot, n: signed counts of the tokens of a text by slot; narrow, as a text stands in one row."""
    dims, unit = encoder.dims, encoder.unit

    def run(batches):
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            for at, piece in T.pieces(b.column(1)):
                cell, sign = _places(piece, dims, unit)
                cell, which = np.unique(cell, return_inverse=True)
                n = np.bincount(which, sign, len(cell)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(ids[at + cell // dims], pa.int64()), pa.array((cell % dims).astype(np.int32)), pa.array(n)], names=[id_col, "slot", "n"])

    return items.select(id_col, "text").mapInArrow(run, f"{id_col} long, slot int, n long")


def tallied(items: DataFrame, dims: int, unit: str, id_col: str = "item_id") -> DataFrame:
    """id, vec (array<int>) of every text: signed counts by slot, from which encoders of the same tokens make their vectors."""

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 1024):
                part = b.slice(at, 1024)
                yield pa.RecordBatch.from_arrays([part.column(0), V.lists(counts(part.column(1), dims, unit).astype(np.int32), pa.int32())], names=[id_col, "vec"])

    return items.select(id_col, "text").mapInArrow(run, f"{id_col} long, vec array<int>")


def dense(items: DataFrame, encoder: HashedEncoder, id_col: str = "item_id") -> DataFrame:
    """id, vec (array<double>) of every text; a text without tokens has the offset in every dimension."""
    e = encoder

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 1024):
                part = b.slice(at, 1024)
                yield pa.RecordBatch.from_arrays([part.column(0), V.lists(finish(e, counts(part.column(1), e.dims, e.unit)))], names=[id_col, "vec"])

    return items.select(id_col, "text").mapInArrow(run, f"{id_col} long, vec array<double>")


@dataclass(frozen=True)
class Finished(Codec):
    """A codec over the vectors of an encoder, made from signed counts: encoders that share counts share a scan of the texts."""

    encoder: HashedEncoder | None = None
    then: Codec = Codec()

    def levels(self):
        return self.then.levels()

    def encode(self, x, c):
        return self.then.encode(finish(self.encoder, x), c)

    def space(self, code, c):
        return self.then.space(code, c)

    def decode(self, code, c):
        return self.then.decode(code, c)

    def bits(self, dims, native=32):
        return self.then.bits(dims, native)


def given(df: DataFrame) -> DataFrame:
    """The stored vectors as they are: item_id, vec."""
    return df.select(F.col("vec_id").alias("item_id"), F.col("embedding").cast("array<double>").alias("vec"))


def lifted_prefix(vec, dims: int, own: int, weight: float = 0.1):
    """Column: vec of `own` dimensions, followed by low-weight projections on hashed +1/-1 directions up to `dims`."""
    rows = F.from_json(F.lit(json.dumps(hash_signs(dims - own, own).tolist())), "array<array<double>>")  # folded to a constant
    x = vec.cast("array<double>")
    return F.concat(x, F.transform(rows, lambda r: F.aggregate(F.zip_with(x, r, lambda a, b: a * b), F.lit(0.0), lambda t, v: t + v) * F.lit(weight / own**0.5)))
