"""Low-precision floats: rounding to a short mantissa as a Column and as a numpy kernel, and packed storage.

A value is rounded half to even at the last mantissa bit of its binade, or of the smallest normal
binade for subnormal values. Beyond the largest finite value the result is infinite, or not a
number for the format that has no infinity, or the largest value itself where saturation is asked for.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class FloatFormat:
    name: str
    mantissa: int
    least_exponent: int
    largest: float
    bits: int
    has_infinity: bool = True


# fixed values: formats by mantissa bits, least normal exponent, largest finite value and width
FORMATS = {
    "fp16": FloatFormat("fp16", 10, -14, 65504.0, 16),
    "bf16": FloatFormat("bf16", 7, -126, 3.3895313892515355e38, 16),
    "fp8_m3": FloatFormat("fp8_m3", 3, -6, 448.0, 8, has_infinity=False),
    "fp8_m2": FloatFormat("fp8_m2", 2, -14, 57344.0, 8),
}


def rounded(v: Column, form: str, saturate: bool = False) -> Column:
    """The double that the format keeps of v."""
    f = FORMATS[form]
    v = v.cast("double")
    size = F.abs(v)
    exponent = F.greatest(F.when(size > 0, F.floor(F.log2(size))).otherwise(f.least_exponent), F.lit(f.least_exponent)).cast("double")
    step = F.pow(F.lit(2.0), exponent - f.mantissa)
    near = F.rint(v / step) * step
    beyond = F.signum(v) * f.largest if saturate else F.signum(v) * float("inf") if f.has_infinity else F.lit(float("nan"))
    return F.when(v.isNull() | F.isnan(v), v).when(F.abs(near) > f.largest, beyond).otherwise(near)


def round_array(x: np.ndarray, form: str, saturate: bool = False) -> np.ndarray:
    """The same in numpy, on any shape."""
    f = FORMATS[form]
    x = np.asarray(x, dtype=np.float64)
    with np.errstate(invalid="ignore", over="ignore"):
        _, e = np.frexp(x)
        step = np.ldexp(1.0, np.maximum(np.where(x == 0, f.least_exponent + 1, e) - 1, f.least_exponent) - f.mantissa)
        near = np.rint(x / step) * step
        beyond = np.sign(x) * (f.largest if saturate else np.inf) if f.has_infinity or saturate else np.full_like(x, np.nan)
        return np.where(np.abs(near) > f.largest, beyond, near)


def pack_floats(x: np.ndarray, form: str) -> np.ndarray:
    """Storage form: sign, exponent and mantissa bits of values that the format holds, as uint8 or uint16."""
    f = FORMATS[form]
    x = round_array(x, form)
    mantissa, exponent = np.frexp(np.abs(x))
    width = f.bits - 1 - f.mantissa
    bias = 1 - f.least_exponent
    normal = (exponent - 1 >= f.least_exponent) & (x != 0)
    finite = np.isfinite(x)
    with np.errstate(invalid="ignore"):
        fraction = np.where(normal, (mantissa * 2 - 1) * (1 << f.mantissa), np.ldexp(np.abs(x), f.mantissa - f.least_exponent))
    field = np.where(normal, exponent - 1 + bias, 0)
    code = (np.where(finite, field, 0).astype(np.int64) << f.mantissa) + np.where(finite, fraction, 0).astype(np.int64)
    top = ((1 << width) - 1) << f.mantissa
    special = np.where(np.isnan(x), top | ((1 << f.mantissa) - 1 if not f.has_infinity else 1 << (f.mantissa - 1)), top)
    code = np.where(finite, code, special) | (np.signbit(x).astype(np.int64) << (f.bits - 1))
    return code.astype(np.uint16 if f.bits == 16 else np.uint8)


def unpack_floats(code: np.ndarray, form: str) -> np.ndarray:
    f = FORMATS[form]
    code = code.astype(np.int64)
    width = f.bits - 1 - f.mantissa
    sign = np.where(code >> (f.bits - 1) & 1, -1.0, 1.0)
    field, fraction = code >> f.mantissa & ((1 << width) - 1), code & ((1 << f.mantissa) - 1)
    bias = 1 - f.least_exponent
    value = np.where(field > 0, np.ldexp(1 + fraction / (1 << f.mantissa), field - bias), np.ldexp(fraction / (1 << f.mantissa), f.least_exponent))
    last = field == (1 << width) - 1
    if f.has_infinity:
        value = np.where(last, np.where(fraction == 0, np.inf, np.nan), value)
    else:
        value = np.where(last & (fraction == (1 << f.mantissa) - 1), np.nan, value)
    return sign * value
