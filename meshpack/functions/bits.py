"""Floats as integers of the same width, in Catalyst expressions.

Spark has no cast between doubles and bytes.  The exponent comes from a base-2 logarithm that
is then corrected by comparison with exact powers of two, the mantissa from exact scaling.
Not-a-number values map to the canonical one; :func:`f64_view` keeps payloads, by Arrow.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T
from .shifts import shl, ushr

#: Fixed values of the two widths: mantissa bits, exponent bias, least normal exponent.
FORMS = {64: (52, 1023, -1022), 32: (23, 127, -126)}
SIGN64 = -(2**63)


def _bits(v: Column, width: int) -> Column:
    mantissa, bias, least = FORMS[width]
    inf = ((1 << (width - 1 - mantissa)) - 1) << mantissa
    nan = inf | 1 << (mantissa - 1)
    v = v.cast("double")
    a = F.abs(v)
    guess = F.floor(F.log2(a))
    e = guess - F.when(F.pow(F.lit(2.0), guess) > a, 1).otherwise(0) + F.when(F.pow(F.lit(2.0), guess + 1) <= a, 1).otherwise(0)
    normal = shl(e + bias, mantissa) + ((a / F.pow(F.lit(2.0), e) - 1.0) * float(1 << mantissa)).cast("long")
    # below the normal range the value is a multiple of the least one; scale in two exact steps
    half = float(2.0 ** ((mantissa - least) // 2))
    rest = float(2.0 ** ((mantissa - least) - (mantissa - least) // 2))
    small = (a * half * rest).cast("long")
    size = (
        F.when(F.isnan(v), F.lit(nan)).when(a == float("inf"), F.lit(inf)).when(a == 0.0, F.lit(0).cast("long"))
        .when(a < 2.0**least, small).otherwise(normal)
    )
    negative = (v < 0) | ((v == 0.0) & v.cast("string").startswith("-"))
    top = F.lit(SIGN64 if width == 64 else 1 << 31)
    return F.when(v.isNull(), None).when(negative & ~F.isnan(v), size.bitwiseOR(top)).otherwise(size)


def f64_bits(v: Column) -> Column:
    """The 64 bits of a double, as a signed bigint."""
    return _bits(v, 64)


def f32_bits(v: Column) -> Column:
    """The 32 bits of a float, in the low half of a bigint."""
    return _bits(v.cast("float"), 32)


def f64_from_bits(b: Column) -> Column:
    """The double of 64 bits; not-a-number values lose their payload."""
    e = ushr(b, 52).bitwiseAND(F.lit(0x7FF)).cast("int")
    m = b.bitwiseAND(F.lit((1 << 52) - 1)).cast("double")
    size = (
        F.when((e == 0x7FF) & (m > 0), F.lit(float("nan"))).when(e == 0x7FF, F.lit(float("inf")))
        .when(e == 0, m * F.lit(2.0**-537) * F.lit(2.0**-537))
        .otherwise((1.0 + m * F.lit(2.0**-52)) * F.pow(F.lit(2.0), (e - 1023).cast("double")))
    )
    return F.when(b < 0, -size).otherwise(size)


def leading_zeros(b: Column, width: int = 64) -> Column:
    """Zero bits above the highest one; all of them for zero."""
    return F.when(b == 0, F.lit(width)).otherwise(F.lit(width) - F.length(F.bin(b)))


@F.arrow_udf(T.LongType())
def f64_view(v: pa.Array) -> pa.Array:
    """The 64 bits of a double by reinterpretation, payloads and signed zeros kept."""
    return v.view(pa.int64())
