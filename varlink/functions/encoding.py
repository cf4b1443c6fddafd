"""Numeric inputs of the networks as column expressions, and their numpy twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def float_bits(x: Column) -> Column:
    """The IEEE binary32 pattern of ``x`` as a signed 32-bit number."""
    return F.reflect(F.lit("java.lang.Float"), F.lit("floatToIntBits"), x.cast("float")).cast("int")


def fixed_bits(x: Column, scale: float = 100.0) -> Column:
    """``x`` scaled and rounded to a signed 32-bit number, ends clipped."""
    return F.round(F.least(F.greatest(x.cast("double") * scale, F.lit(-(2.0**31) + 1)), F.lit(2.0**31 - 1))).cast("int")


def bits_to_array(n: Column, width: int = 32) -> Column:
    """Bits of an integer, the sign (highest) first."""
    return F.transform(F.sequence(F.lit(width - 1), F.lit(0)), lambda i: F.call_function("getbit", n, i).cast("int"))


def encode_bits32(x: Column, form: str = "ieee754") -> Column:
    """32 binary features: sign, exponent, fraction (``ieee754``), or sign and magnitude of a scaled integer."""
    if form == "ieee754":
        return bits_to_array(float_bits(x))
    n = fixed_bits(x)
    return F.concat(F.array((n < 0).cast("int")), bits_to_array(F.abs(n), 31))


def encode_raw(x: Column) -> Column:
    return F.array(x.cast("float").cast("double"))


def exponent(x: Column) -> Column:
    """floor(log2 |x|), put right where the logarithm rounds over a power of two; 0 for 0."""
    a = F.abs(x.cast("double"))
    e = F.floor(F.log2(a)).cast("int")
    e = F.when(F.pow(F.lit(2.0), e) > a, e - 1).when(F.pow(F.lit(2.0), e + 1) <= a, e + 1).otherwise(e)
    return F.when(a == 0, F.lit(0)).otherwise(e)


def encode_exp_mantissa(x: Column) -> Column:
    """``[exponent, mantissa]``: x = mantissa * 2^exponent with 1 <= |mantissa| < 2; zeros give [0, 0]."""
    e = exponent(x)
    return F.array(e.cast("double"), F.when(x == 0, F.lit(0.0)).otherwise(x.cast("double") / F.pow(F.lit(2.0), e)))


# numpy twins, used inside the Arrow kernels


def np_bits32(x: np.ndarray, form: str = "ieee754", scale: float = 100.0) -> np.ndarray:
    x = np.asarray(x, np.float64)
    if form == "ieee754":
        n = x.astype(np.float32).view(np.uint32)
        return (n[:, None] >> np.arange(31, -1, -1, dtype=np.uint32) & 1).astype(np.float64)
    n = np.rint(np.clip(x * scale, -(2.0**31) + 1, 2.0**31 - 1)).astype(np.int64)
    bits = np.abs(n)[:, None] >> np.arange(30, -1, -1) & 1
    return np.concatenate([(n < 0)[:, None], bits], axis=1).astype(np.float64)


def np_raw(x: np.ndarray) -> np.ndarray:
    return np.asarray(x, np.float32).astype(np.float64)[:, None]


def np_exp_mantissa(x: np.ndarray) -> np.ndarray:
    m, e = np.frexp(np.asarray(x, np.float64))
    return np.stack([np.where(x == 0, 0, e - 1), m * 2], axis=1).astype(np.float64)


NUMERIC_ENCODERS = {"bits": (np_bits32, 32), "fixed": (lambda x: np_bits32(x, "fixed32"), 32), "raw": (np_raw, 1), "exp_mantissa": (np_exp_mantissa, 2)}
