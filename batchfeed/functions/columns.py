"""Small column expressions: exact rounding, guarded ratios, time as integers."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def rounded(x: Column) -> Column:
    """Six decimals by floor(x * 1e6 + 0.5) / 1e6, alike in every engine."""
    return F.floor(x * 1e6 + 0.5) / F.lit(1e6)


def ratio(a: Column, b: Column) -> Column:
    """a / b as a rounded double, null where b is 0."""
    return rounded(a.cast("double") / F.nullif(b.cast("double"), F.lit(0.0)))


def micros(ts: Column) -> Column:
    """Microseconds since 1970 of a TIMESTAMP_NTZ or TIMESTAMP."""
    return F.unix_micros(ts.cast("timestamp"))


def div(a: Column, b: Column | int) -> Column:
    """Integer quotient as BIGINT."""
    return F.call_function("div", a.cast("long"), F.lit(b).cast("long") if isinstance(b, int) else b.cast("long"))
