"""Joins that Spark has no single operator for: interval overlap and as-of."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, width: int) -> DataFrame:
    """Pairs of half-open integer intervals (a1, a2 | b1, b2) that overlap.

    Each interval is copied into the buckets of ``width`` that it meets; a pair is kept in the bucket where the
    later of the two starts, so it appears once.
    """
    spread = lambda df, lo, hi: df.withColumn("bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    pairs = spread(left, "a1", "a2").join(spread(right, "b1", "b2"), "bucket")
    meets = (F.col("a1") < F.col("b2")) & (F.col("b1") < F.col("a2"))
    return pairs.where(meets & (F.floor(F.greatest("a1", "b1") / width) == F.col("bucket"))).drop("bucket")


def as_of(left: DataFrame, right: DataFrame, by: list[str], at: str, value: str, tie: Column | None = None) -> DataFrame:
    """left with the last ``value`` of right at or before ``at`` within ``by``: one union and one window, no pairs."""
    a = left.withColumns({"__side": F.lit(1), "__v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(*by, at, F.col(value).alias("__v")).withColumn("__side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(*by).orderBy(at, "__side", *([tie] if tie is not None else [])).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").drop("__side", "__v")
