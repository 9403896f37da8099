import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from compresslab.functions import rounding as R

EDGES = [0.0, -0.0, 1.0, -1.0, 2.0**-14, 2.0**-24, 448.0, 449.0, 464.0, 480.0, 57344.0, 61440.0, 65504.0, 65520.0, 1e38, float("nan"), 1.0625, 1.1875, 2.0**-9, 2.0**-10]


def test_half_precision_is_numpys():
    x = np.array(EDGES + list(np.random.default_rng(0).normal(size=2000) * 10))
    with np.errstate(over="ignore"):
        assert np.array_equal(R.round_array(x, "fp16"), x.astype(np.float16).astype(float), equal_nan=True)


def test_bfloat16_is_bit_rounding():
    x = np.random.default_rng(1).normal(size=2000).astype(np.float32)
    bits = x.view(np.uint32)
    near = ((bits + 0x7FFF + ((bits >> 16) & 1)) >> 16 << 16).view(np.float32)
    assert np.array_equal(R.round_array(x, "bf16"), near.astype(float))


@pytest.mark.parametrize("form", list(R.FORMATS))
def test_column_equals_kernel(spark, form):
    x = EDGES + list(np.random.default_rng(2).normal(size=200))
    got = [r[0] for r in spark.createDataFrame([(float(v),) for v in x], "v double").select(R.rounded(F.col("v"), form)).collect()]
    assert np.array_equal(np.array(got), R.round_array(np.array(x), form), equal_nan=True)


@pytest.mark.parametrize("form", ["fp8_m3", "fp8_m2"])
def test_all_codes_of_8_bit_floats(form):
    codes = np.arange(256, dtype=np.uint8)
    values = R.unpack_floats(codes, form)
    finite = np.isfinite(values)
    assert np.array_equal(R.round_array(values[finite], form), values[finite])
    back = R.pack_floats(values, form)
    assert np.array_equal(back[finite], codes[finite])
    assert R.FORMATS[form].largest == values[finite].max()


def test_overflow_rules():
    assert np.isnan(R.round_array(np.array([480.0]), "fp8_m3")[0]) and R.round_array(np.array([464.0]), "fp8_m3")[0] == 448
    assert R.round_array(np.array([480.0]), "fp8_m3", True)[0] == 448
    assert np.isinf(R.round_array(np.array([61440.0]), "fp8_m2")[0]) and np.isinf(R.round_array(np.array([65520.0]), "fp16")[0])


@settings(max_examples=60, deadline=None)
@given(st.floats(-400, 400, allow_nan=False), st.sampled_from(list(R.FORMATS)))
def test_casting_is_idempotent_and_close(v, form):
    y = R.round_array(np.array([v]), form)
    assert np.array_equal(R.round_array(y, form), y)
    assert abs(y[0] - v) <= max(abs(v) * 2.0 ** -(R.FORMATS[form].mantissa + 1), 2.0 ** (R.FORMATS[form].least_exponent - R.FORMATS[form].mantissa - 1)) * (1 + 1e-12)
