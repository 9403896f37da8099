"""Grids of codecs: cutoffs of a dimension family, LSH and PQ settings of equal ratios, and the full product."""

from __future__ import annotations

from ..operators import codecs as K

# fixed values: cutoffs of the 1024-dimensional family; others keep the ratios
BASE = (32, 64, 128, 256, 512, 768)


def cutoffs(dims: int) -> list[int]:
    return [max(1, c * dims // 1024) for c in BASE]


def lsh(dims: int, native: int = 32, ratios=(4, 8, 16, 32)) -> list[K.Codec]:
    return [K.lsh(dims * native // r) for r in ratios]


def pq(dims: int, native: int = 32) -> list[K.Codec]:
    """Six settings (subvectors, bits): at 4x, two each at 8x and 16x, and at 32x."""
    return [K.pq(dims, 8), K.pq(dims // 2, 8), K.pq(dims, 4), K.pq(dims // 4, 8), K.pq(dims // 2, 4), K.pq(dims // 8, 8)]


def casts() -> list[K.Codec]:
    return [K.float_cast(f) for f in ("fp16", "bf16", "fp8_m3", "fp8_m2")]


def scalar(scoring: str = "raw") -> list[K.Codec]:
    return [K.equal_width(b, scoring=scoring) for b in (8, 4, 2)] + [K.percentile_bins(b, scoring) for b in (8, 4, 2)]


def bits() -> list[K.Codec]:
    return [K.binary("zero"), K.binary("median")]


def stateless_and_calibrated(dims: int, scoring: str = "raw") -> list[K.Codec]:
    """Uncompressed, casts, bins and bits on all dimensions and on each cutoff."""
    inner = [*casts(), *scalar(scoring), *bits()]
    out: list[K.Codec] = [K.identity(), *inner]
    for x in cutoffs(dims):
        out += [K.truncate(x), *(K.compose(K.truncate(x), c) for c in inner)]
    return out


def full(dims: int, native: int = 32) -> list[K.Codec]:
    return [*stateless_and_calibrated(dims), *(K.pca(x) for x in cutoffs(dims)), *lsh(dims, native), *pq(dims, native)]


def paper_like(dims: int, native: int = 32, ratios=(1, 2, 4, 8, 16, 32)) -> list[K.Codec]:
    """The cells whose ratio is one of those that are compared."""
    return [c for c in full(dims, native) if any(abs(c.ratio(dims, native) - r) < 1e-9 for r in ratios)]
