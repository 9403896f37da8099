"""Words and runs of three characters of text columns, without a Python object for each token."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def pieces(column: pa.Array, rows: int = 2048, size: int = 1 << 20) -> Iterator[tuple[int, pa.Array]]:
    """(start, slice) of a column in pieces of about `size` bytes; a longer text is a piece of its own."""
    end = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False))])
    at = 0
    while at < len(column):
        to = min(at + rows, max(at + 1, int(np.searchsorted(end, end[at] + size, side="right")) - 1))
        yield at, column.slice(at, to - at)
        at = to


def words(column: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """(row, word) of all runs of letters, in lower case; a null has none."""
    lists = pc.split_pattern_regex(pc.utf8_lower(pc.fill_null(column, "")), pattern=r"[^\p{L}]+")
    flat = lists.flatten()
    full = pc.binary_length(flat).to_numpy(zero_copy_only=False) > 0
    row = np.repeat(np.arange(len(column)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
    return row[full], flat.filter(pa.array(full))


def grams(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(row, number) of all runs of three characters, in lower case; 21 bits of the number are a character."""
    low = pc.utf8_lower(pc.fill_null(column, ""))
    u = np.frombuffer("".join(low.to_pylist()).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    row = np.repeat(np.arange(len(column)), pc.utf8_length(low).to_numpy(zero_copy_only=False))
    if len(u) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    key = (u[:-2] << np.uint64(42)) | (u[1:-1] << np.uint64(21)) | u[2:]
    whole = row[:-2] == row[2:]
    return row[:-2][whole], key[whole]


def gram_text(key: int) -> str:
    return chr(key >> 42) + chr(key >> 21 & 0x1FFFFF) + chr(key & 0x1FFFFF)


_SHIFTS = np.repeat(np.array([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]], np.uint32), 4, axis=0).ravel()
_SINES = np.array([int(abs(math.sin(i + 1)) * 2**32) for i in range(64)], np.uint32)
_START = tuple(np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))


def digests(words: pa.Array) -> np.ndarray:
    """The first 8 hex digits of the md5 of every word, as numbers: one block of md5 for many words at once."""
    size = pc.binary_length(words).to_numpy(zero_copy_only=False)
    short = size <= 55  # others take more than a block
    out = np.empty(len(words), np.int64)
    out[~short] = [int(hashlib.md5(w.encode()).hexdigest()[:8], 16) for w in words.filter(pa.array(~short)).to_pylist()]
    kept = words.filter(pa.array(short)).cast(pa.large_string())
    flat = np.frombuffer(kept.buffers()[2] or b"", np.uint8)[np.frombuffer(kept.buffers()[1], np.int64)[kept.offset] if len(kept) else 0 :]
    size, found, used = size[short], [], 0
    for at in range(0, len(size), 8192):
        n = size[at : at + 8192]
        block = np.zeros((len(n), 64), np.uint8)
        block[np.arange(64) < n[:, None]] = flat[used : used + int(n.sum())]
        used += int(n.sum())
        block[np.arange(len(n)), n] = 0x80
        block[:, 56], block[:, 57] = n * 8 & 255, n * 8 >> 8
        found.append(_md5_head(np.ascontiguousarray(block.view("<u4").T)).byteswap())
    out[short] = np.concatenate([*found, np.zeros(0, np.uint32)])
    return out


def _md5_head(m: np.ndarray) -> np.ndarray:
    """The first word of the md5 of messages of one block; m: 16 words x messages."""
    a, b, c, d = (np.full(m.shape[1], x, np.uint32) for x in _START)
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f += a
        f += m[g]
        f += _SINES[i]
        turned = f << _SHIFTS[i]
        f >>= np.uint32(32) - _SHIFTS[i]
        turned |= f
        turned += b
        a, d, c, b = d, c, b, turned
    return a + _START[0]
