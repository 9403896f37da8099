import numpy as np
import pytest

from compresslab.operators import calibrate, codecs
from compresslab.plans import grids


def calibration(x, levels=calibrate.LEVELS):
    return calibrate.Calibration({q: np.quantile(x, q, axis=0) for q in levels}, x.min(axis=0), x.max(axis=0))


X = np.random.default_rng(0).normal(size=(4096, 8))
CAL = calibration(X)


def test_spark_quantiles_are_numpys(spark):
    x = X[:200]
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    c = calibrate.quantiles(df, (0.025, 0.5, 0.975))
    for q in (0.025, 0.5, 0.975):
        assert np.allclose(c.at(q), np.quantile(x, q, axis=0), atol=1e-11)
    sketch = calibrate.quantiles(df, (0.5,), method="kll")
    assert np.abs(sketch.at(0.5) - c.at(0.5)).max() < 0.2


@pytest.mark.parametrize("bits", [8, 4, 2])
def test_bins(bits):
    equal, even = codecs.equal_width(bits), codecs.percentile_bins(bits)
    a, b = equal.encode(X, CAL), even.encode(X, CAL)
    assert a.min() == 0 and a.max() == 2**bits - 1 and b.min() == 0 and b.max() == 2**bits - 1
    counts = np.bincount(b[:, 0].astype(int), minlength=2**bits)
    assert abs(counts - len(X) / 2**bits).max() <= 1
    order = np.argsort(X[:, 0])
    assert (np.diff(a[order, 0]) >= 0).all() and (np.diff(b[order, 0]) >= 0).all()
    assert (a[:, 0] == 0).mean() >= 0.025 and (a[:, 0] == 2**bits - 1).mean() >= 0.025


def test_clip_shields_from_an_outlier():
    x = np.append(np.arange(100.0), 1e6)[:, None]
    c = calibration(x)
    assert len(np.unique(codecs.equal_width(4).encode(x, c))) == 16
    assert len(np.unique(codecs.equal_width(4, None).encode(x, c))) == 2


def test_constant_dimension_and_zero_vector():
    x = np.zeros((10, 2))
    c = calibration(x)
    assert (codecs.equal_width(8).encode(x, c) == 0).all()
    assert codecs.percentile_bins(2).encode(x, c).shape == (10, 2)


def test_binary():
    assert abs(codecs.binary("median").encode(X, CAL).mean() - 0.5) < 1e-3
    assert np.array_equal(codecs.binary("zero").encode(X, CAL), codecs.binary("zero").encode(3 * X, CAL))


def test_truncation_and_ratios():
    assert np.array_equal(codecs.truncate(8).encode(X, CAL), X)
    assert codecs.compose(codecs.truncate(4), codecs.percentile_bins(4)).ratio(8) == 16
    assert codecs.float_cast("fp16").ratio(8, native=16) == 1
    assert [c.ratio(64) for c in grids.lsh(64)] == [4, 8, 16, 32] and [c.ratio(64) for c in grids.pq(64)] == [4, 8, 8, 16, 16, 32]
    assert len(grids.full(64)) == 107 and grids.cutoffs(768) == [24, 48, 96, 192, 384, 576]


def test_principal_directions(spark):
    g = np.random.default_rng(1)
    x = g.normal(size=(300, 1)) * np.array([[3.0, 4.0, 0.0]]) + g.normal(size=(300, 3)) * 0.1
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    c = calibrate.principal(df)
    _, _, right = np.linalg.svd(x - x.mean(axis=0))
    assert np.allclose(np.abs(c.basis), np.abs(right), atol=1e-6) and np.allclose(c.basis @ c.basis.T, np.eye(3), atol=1e-9)
    assert np.allclose(c.basis[0], [0.6, 0.8, 0.0], atol=0.02) and (np.diff(c.variance) <= 1e-12).all()
    full = codecs.pca(3).encode(x, c)
    assert np.allclose(np.linalg.norm(full[0] - full[1]), np.linalg.norm(x[0] - x[1]))
    errors = [((codecs.pca(k).decode(codecs.pca(k).encode(x, c), c) - x) ** 2).sum() for k in (1, 2, 3)]
    assert errors[0] >= errors[1] >= errors[2] and errors[2] < 1e-9


def test_lsh_disagreement_is_the_angle():
    codec = codecs.lsh(8192)
    for degrees in (0, 60, 90, 180):
        a = np.radians(degrees)
        v = np.array([[1.0, 0.0], [np.cos(a), np.sin(a)]])
        code = codec.encode(v, calibrate.Calibration())
        assert abs((code[0] != code[1]).mean() - degrees / 180) < 0.02


def test_lsh_medians_split_in_half(spark):
    x = X[:400] + 3.0
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    codec = codecs.lsh(16, thresholds="median")
    assert abs(codec.encode(x, codecs.fit_lsh(df, codec)).mean(axis=0) - 0.5).max() < 0.01
    assert abs(codecs.lsh(16).encode(x, calibrate.Calibration()).mean(axis=0) - 0.5).max() > 0.3


def test_pq_finds_clusters(spark):
    g = np.random.default_rng(2)
    centres = np.array([[0.0, 0.0, 5.0, 5.0], [9.0, 9.0, -5.0, -5.0]])
    x = centres[g.integers(0, 2, 64)]
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<double>")
    c = codecs.train_pq(df, 2, 1)
    codec = codecs.pq(2, 1)
    assert np.allclose(codec.space(codec.encode(x, c), c), x)


def test_lloyd_never_gets_worse():
    g = np.random.default_rng(3)
    p = g.normal(size=(500, 3))
    cost = lambda c: ((p[:, None] - c[None]) ** 2).sum(axis=2).min(axis=1).sum()
    start = p[:8].copy()
    costs = [cost(codecs.lloyd(p, start, n)) for n in range(6)]
    assert all(a >= b - 1e-9 for a, b in zip(costs, costs[1:]))


def test_packed_size():
    for codec in (codecs.percentile_bins(4), codecs.binary("zero"), codecs.float_cast("fp8_m3"), codecs.compose(codecs.truncate(4), codecs.equal_width(2))):
        code = codec.encode(X[:1], CAL)[0]
        assert len(codecs.to_bytes(codec, code)) == -(-codec.bits(8) // 8)
