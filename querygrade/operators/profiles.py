"""Error classes, resources and costs from run logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from querygrade.functions.units import share

#: Ordered rules (class, pattern of SQLSTATE or "", pattern of the text or ""); the first that matches wins.
ERROR_RULES = [
    (1, "^(08...|57P0.)$", ""),
    (1, "", "connection (reset|closed|refused)|server closed|decode|encoding|driver"),
    (5, "", "parse error.*geometry|invalid (wkt|wkb|hex|geometry)|unknown geometry type|unclosed ring|box3d"),
    (6, "", "mixed srid|srid mismatch|unknown srid|cannot find srid|dimensions? (mismatch|differ)"),
    (3, "^(42P01|42703|42704|3F000)$", ""),
    (4, "^(42883|42605|42725)$", ""),
    (4, "", "function .*does not exist|cannot resolve routine|no (function|operator) matches|wrong number of arguments"),
    (3, "", "(relation|table|view|column|type) .*(does not exist|cannot be found|cannot be resolved)"),
    (2, "^42...$", ""),
    (2, "", "syntax error|parse|unterminated|mismatched input"),
    (7, "^22...$", ""),
    (7, "", "division by zero|invalid input|overflow|cast"),
    (8, "^(57014|53...)$", ""),
    (8, "", "cancel|timeout|out of memory|row cap"),
]
OTHER = 9


def classify_error(text: Column, state: Column | None = None, rules: list[tuple[int, str, str]] = ERROR_RULES) -> Column:
    """Class of an error by ordered rules; null text is no error."""
    low = F.lower(text)
    out = F.lit(OTHER)
    for number, state_rule, text_rule in reversed(rules):
        if state_rule and state is not None:
            out = F.when(state.rlike(state_rule), number).otherwise(out)
        elif text_rule:
            out = F.when(low.rlike(text_rule), number).otherwise(out)
    return F.when(text.isNotNull(), out)


def sql_classify(text: str, rules: list[tuple[int, str, str]] = ERROR_RULES) -> str:
    """The DuckDB spelling of the text rules."""
    cases = " ".join(f"WHEN regexp_matches(lower({text}), '{t}') THEN {n}" for n, s, t in rules if t)
    return f"CASE WHEN {text} IS NULL THEN NULL {cases} ELSE {OTHER} END"


def error_profile(log: DataFrame, by: list[str]) -> DataFrame:
    """by..., class, n, share of the failed attempts."""
    each = log.where("class is not null").groupBy(*by, "class").agg(F.count(F.lit(1)).alias("n"))
    return each.withColumn("share", share(F.col("n"), F.sum("n").over(Window.partitionBy(*by))))


def dominant_classes(profile: DataFrame, by: list[str], most: int = 2) -> DataFrame:
    """by..., share of the ``most`` largest classes together."""
    w = Window.partitionBy(*by).orderBy(F.desc("n"), "class")
    return profile.withColumn("r", F.row_number().over(w)).where(F.col("r") <= most).groupBy(*by).agg(F.sum("share").alias("dominance"))


def error_shift(profile: DataFrame, first: str, second: str, of: str = "family") -> DataFrame:
    """class, delta: share in ``second`` minus share in ``first``."""
    wide = profile.groupBy("class").pivot(of, [first, second]).agg(F.first("share"))
    return wide.select("class", (F.coalesce(second, F.lit(0.0)) - F.coalesce(first, F.lit(0.0))).alias("delta"))


def resource_summary(log: DataFrame, by: list[str]) -> DataFrame:
    """Mergeable sums with their means."""
    sums = log.groupBy(*by).agg(F.sum("tokens").alias("tokens"), F.sum("seconds").alias("seconds"), F.count(F.lit(1)).alias("n"))
    return sums.select(*by, "n", (F.col("tokens") / F.col("n")).alias("mean_tokens"), (F.col("seconds") / F.col("n")).alias("mean_seconds"))


def running_means(log: DataFrame, by: list[str], order: list[str], value: str) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return log.withColumn("mean_so_far", F.avg(value).over(w))


def cost_effectiveness(table: DataFrame) -> DataFrame:
    """Accuracy for a thousand tokens and for a second."""
    return table.withColumns({"per_1k_tokens": F.try_divide(F.col("accuracy") * 1000, F.col("mean_tokens")), "per_second": F.try_divide(F.col("accuracy"), F.col("mean_seconds"))})


def stage_hours(stages: DataFrame) -> DataFrame:
    """stage, hours with a total row (null stage)."""
    return stages.rollup("stage").agg(F.sum("hours").alias("hours"))
