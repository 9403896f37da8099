"""Vectorised word scanner: hashes of all words of a batch of texts in a few numpy passes.

A word is a maximal run of ASCII letters, ASCII digits and bytes above 0x7F, so words of any
script stay whole and punctuation of the ASCII range separates. Case is folded for ASCII and the
Latin-1 letters of UTF-8 before hashing.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_MUL = np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x100000001B3 | 1
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply rounds)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = max(n, 1 << 20)
        tables = []
        for base in (_BASE, _BASE_INVERSE):
            steps = np.full(size, base, dtype=np.uint64)
            steps[0] = 1
            tables.append(np.multiply.accumulate(steps))
        _powers[:] = tables
    return _powers[0][:n], _powers[1][:n]


def _lookup(predicate) -> np.ndarray:
    return np.array([predicate(b) for b in range(256)], dtype=bool)


_WORD = _lookup(lambda b: b >= 0x80 or chr(b).isalnum())
_DIGIT = _lookup(lambda b: 0x30 <= b <= 0x39)
_UPPER = _lookup(lambda b: 0x41 <= b <= 0x5A)
_LOWERED = np.array([b + 32 if 0x41 <= b <= 0x5A else b for b in range(256)], dtype=np.uint8)


def fold_case(raw: np.ndarray) -> np.ndarray:
    """Lower case for ASCII and for the letters U+00C0 to U+00DE in UTF-8."""
    low = _LOWERED[raw]
    if len(raw) > 1:
        second = np.flatnonzero((raw[:-1] == 0xC3) & (raw[1:] >= 0x80) & (raw[1:] <= 0x9E) & (raw[1:] != 0x97)) + 1
        low[second] += 0x20
    return low


@dataclass
class Words:
    doc: np.ndarray  # row of the text each word stands in
    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    first: np.ndarray  # index of the first word of every text, with one more at the end

    def __len__(self) -> int:
        return len(self.start)


def scan(raw: np.ndarray, offsets: np.ndarray) -> Words:
    """Words of the texts that lie one after the other in raw; offsets as in an Arrow string column."""
    n_docs = len(offsets) - 1
    inside = np.zeros(len(raw) + 2, dtype=np.int8)
    inside[1:-1] = _WORD[raw]
    change = np.diff(inside)
    start, end = np.flatnonzero(change == 1), np.flatnonzero(change == -1)
    # a text's end also ends a word
    cuts = offsets[1:-1]
    if len(cuts) and len(start):
        word = np.searchsorted(start, cuts, side="right") - 1
        cuts = np.unique(cuts[(word >= 0) & (start[word] < cuts) & (cuts < end[word])])
        if len(cuts):
            start, end = np.sort(np.concatenate([start, cuts])), np.sort(np.concatenate([end, cuts]))
    doc = np.searchsorted(offsets, start, side="right") - 1
    power, inverse = _power_tables(len(raw) + 1)
    sums = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum((fold_case(raw).astype(np.uint64) + np.uint64(1)) * power[: len(raw)], out=sums[1:])
    hashed = mix((sums[end] - sums[start]) * inverse[start] + (end - start).astype(np.uint64) * _MUL)
    first = np.searchsorted(doc, np.arange(n_docs + 1))
    return Words(doc.astype(np.int64), start, end, hashed, first)


def shingle_hashes(words: Words, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every run of k words inside a text; a text of fewer words (one at least) gives one short run."""
    n = len(words)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    total = np.zeros(n, dtype=np.uint64)
    for i in range(k):
        coefficient = np.uint64(pow(0xD6E8FEB86659FD93, i + 1, 1 << 64))
        if i < n:
            total[: n - i] += words.hash[i:] * coefficient
    counts = np.diff(words.first)
    valid = np.zeros(n, dtype=bool)
    if n >= k:
        valid[: n - k + 1] = words.doc[: n - k + 1] == words.doc[k - 1 :]
    docs, hashes = words.doc[valid], mix(total[valid])
    short = np.flatnonzero((counts > 0) & (counts < k))
    if len(short):
        coefficients = np.array([pow(0xD6E8FEB86659FD93, i + 1, 1 << 64) for i in range(k)], dtype=np.uint64)
        extra = np.zeros(len(short), dtype=np.uint64)
        for j, d in enumerate(short):
            h = words.hash[words.first[d] : words.first[d + 1]]
            extra[j] = (h * coefficients[: len(h)]).sum(dtype=np.uint64)
        extra += counts[short].astype(np.uint64)
        docs, hashes = np.concatenate([docs, short]), np.concatenate([hashes, mix(extra)])
        order = np.argsort(docs, kind="stable")
        docs, hashes = docs[order], hashes[order]
    return docs, hashes


def spaced(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Case-folded bytes in which any run of separators is one blank; every text starts and ends with one."""
    low = fold_case(raw)
    letter = _WORD[raw] & ~_DIGIT[raw]
    low = np.where(letter, low, np.uint8(32))
    n = len(offsets) - 1
    lengths = np.diff(offsets)
    placed = np.full(len(raw) + 2 * n, 32, dtype=np.uint8)
    shift = np.repeat(np.arange(n) * 2 + 1, lengths)
    placed[np.arange(len(raw)) + shift] = low
    bounds = offsets + 2 * np.arange(n + 1)
    keep = np.ones(len(placed), dtype=bool)
    if len(placed) > 1:
        keep[1:] = (placed[1:] != 32) | (placed[:-1] != 32)
        keep[bounds[:-1][bounds[:-1] < len(placed)]] = True
    kept = np.concatenate([[0], np.cumsum(keep)])
    return placed[keep], kept[bounds]
