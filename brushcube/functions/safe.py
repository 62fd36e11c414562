"""Null-, ANSI- and NaN-safe helpers, only where Spark's own function differs from what the methods need."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def ratio(a: Column, b: Column) -> Column:
    """a / b, null where b is 0 (ANSI mode would raise)."""
    return F.try_divide(a, b)


def clamp(m: Column) -> Column:
    """Rounding may leave a sum of squares a little below 0."""
    return F.greatest(m, F.lit(0.0))


def count_or_zero(c: Column) -> Column:
    """A count merged over no cells is 0, not null."""
    return F.coalesce(c, F.lit(0)).cast("long")


def text_number(x: float) -> str:
    """A double literal that Spark and an ANSI engine read alike (bare 0.1 would be a decimal)."""
    return f"CAST({x!r} AS DOUBLE)"


def epoch_days(col: str) -> str:
    """Days since 1970-01-01 of a time column, as SQL text."""
    return f"unix_date(CAST({col} AS DATE))"


def epoch_seconds(col: str) -> str:
    """Seconds since 1970-01-01 of a time column without zone, as SQL text (session zone UTC)."""
    return f"unix_seconds(CAST({col} AS TIMESTAMP))"
