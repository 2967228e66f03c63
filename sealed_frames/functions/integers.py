"""Exact integer forms of money and time (L791): expressions on JVM functions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def cents(x: str | Column) -> Column:
    """A decimal amount in hundredths."""
    return F.round(_c(x) * 100).cast("long")


def revenue(price: str | Column = "price", discount: str | Column = "disc") -> Column:
    """price * (100 - discount): hundredths of a cent, exact."""
    return _c(price) * (100 - _c(discount))


def day_number(x: str | Column) -> Column:
    """Days since 1970-01-01."""
    return F.datediff(_c(x), F.lit("1970-01-01").cast("date")).cast("long")


def per_mille(part: str | Column, whole: str | Column) -> Column:
    """1000 * part / whole, truncated; both non-negative."""
    return F.call_function("div", _c(part) * 1000, _c(whole))
