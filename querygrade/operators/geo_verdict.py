"""Verdicts on geometry cells: text equality first, then snapped topology with heights, then no."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from querygrade.functions.geometry_udfs import verdict_of
from querygrade.sources.tables import spread


def geo_verdict(pairs: DataFrame, rule: str = "full") -> DataFrame:
    """``pairs(..., ref, got)`` with verdict 0/1.  Rules: text, exact (text or exact topology), full.

    One Arrow function decides each pair in one pass and stops at the first test that settles it.  Two nulls agree; null
    against a value, and invalid texts, do not.
    """
    known = F.when(F.col("ref").isNull() & F.col("got").isNull(), 1).when(F.col("ref").isNull() | F.col("got").isNull(), 0)
    return spread(pairs).withColumn("verdict", F.coalesce(known, verdict_of(rule)("ref", "got")))
