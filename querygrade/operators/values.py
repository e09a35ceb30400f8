"""Comparison of result cells: text, numbers and booleans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from querygrade.functions.units import norm_value


def same_value(a: Column, b: Column, num_tol: float | None = None) -> Column:
    """Equal after normalisation; two nulls are equal; with ``num_tol`` numbers may differ by it."""
    same = norm_value(a).eqNullSafe(norm_value(b))
    if num_tol is not None:
        close = F.abs(a.try_cast("double") - b.try_cast("double")) <= num_tol
        same = same | F.coalesce(close, F.lit(False))
    return same


def value_verdict(reference: DataFrame, answer: DataFrame, keys: list[str], order: str = "position", num_tol: float | None = None) -> DataFrame:
    """keys, ok: all cells (col, row, value) of a statement agree, with equal numbers of rows and columns.

    position: by row number, as the method has it; multiset: rows of a column in any order.
    """
    if order == "multiset":
        def counted(cells: DataFrame, name: str) -> DataFrame:
            return cells.groupBy(*keys, "col", norm_value(F.col("value")).alias("v")).agg(F.count(F.lit(1)).alias(name))

        a, b = counted(reference, "na"), counted(answer, "nb")
        on = [a[k].eqNullSafe(b[k]) for k in [*keys, "col", "v"]]
        met = a.join(b, on, "full").select(*[F.coalesce(a[k], b[k]).alias(k) for k in keys], F.coalesce(F.col("na") == F.col("nb"), F.lit(False)).alias("ok"))
    else:
        at = [*keys, "col", "row"]
        a = reference.select(*at, F.col("value").alias("va"), F.lit(True).alias("ina"))
        b = answer.select(*at, F.col("value").alias("vb"), F.lit(True).alias("inb"))
        met = a.join(b, at, "full").select(*keys, (F.coalesce(F.col("ina") & F.col("inb"), F.lit(False)) & same_value(F.col("va"), F.col("vb"), num_tol)).alias("ok"))
    return met.groupBy(*keys).agg(F.bool_and("ok").cast("int").alias("ok"))
