"""Bit shifts by a number or a column."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _shift(name: str, x, n) -> Column:
    return F.call_function(name, F.col(x) if isinstance(x, str) else x, n if isinstance(n, Column) else F.lit(n))


def shl(x, n) -> Column:
    return _shift("shiftleft", x, n)


def shr(x, n) -> Column:
    return _shift("shiftright", x, n)


def ushr(x, n) -> Column:
    return _shift("shiftrightunsigned", x, n)
