"""Engine-neutral pseudo-random numbers and text normalisation."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def unit(text: Column) -> Column:
    """First seven hex digits of md5 as a whole number; the same in any SQL engine."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 7), 16, 10).cast("long")


def unit_of(*parts) -> Column:
    return unit(F.concat(*[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]))


def norm_value(text: Column) -> Column:
    """All white space dropped, lower case."""
    return F.lower(F.regexp_replace(text, r"[ \t\n\r\f\x0b]+", ""))


def share(part: Column, whole: Column) -> Column:
    """part / whole, null where the whole is 0."""
    return F.try_divide(part.cast("double"), whole.cast("double"))


def sql_unit(text: str) -> str:
    """The DuckDB spelling of ``unit``."""
    return f"CAST('0x' || substr(md5({text}), 1, 7) AS BIGINT)"
