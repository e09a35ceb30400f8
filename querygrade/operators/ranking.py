"""Entropy-weighted two-stage ranking on a long table (model_id, metric, value); never a driver matrix."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def long_metrics(table: DataFrame, metrics: list[str], key: str = "model_id") -> DataFrame:
    return table.unpivot([key], metrics, "metric", "value")


def scale_metrics(long: DataFrame, norm: str = "minmax", cost: tuple[str, ...] = ()) -> DataFrame:
    """model_id, metric, x: values on a common scale; measures of cost are flipped."""
    w = Window.partitionBy("metric")
    low, high, total = F.min("value").over(w), F.max("value").over(w), F.sum("value").over(w)
    flip = F.col("metric").isin(*cost) if cost else F.lit(False)
    value = F.col("value")
    if norm == "minmax":
        x = F.coalesce(F.try_divide(value - low, high - low), F.lit(0.0))
        x = F.when(flip, 1 - x).otherwise(x)
    elif norm == "max":
        x = F.coalesce(F.try_divide(F.when(flip, high - value).otherwise(value), high), F.lit(0.0))
    elif norm == "sum":
        x = F.coalesce(F.try_divide(F.when(flip, high - value).otherwise(value), total), F.lit(0.0))
    else:
        x = F.when(flip, high - value).otherwise(value)
    return long.select("model_id", "metric", x.alias("x"))


def metric_entropy(scaled: DataFrame) -> DataFrame:
    """metric, e: entropy of the shares over ln of the number of contestants; 1 for one contestant or no mass."""
    w = Window.partitionBy("metric")
    p = scaled.withColumn("p", F.try_divide("x", F.sum("x").over(w)))
    term = F.when(F.col("p") > 0, F.col("p") * F.ln("p")).otherwise(0.0)
    out = p.groupBy("metric").agg(F.sum(term).alias("s"), F.count(F.lit(1)).alias("m"), F.sum("x").alias("mass"))
    return out.select("metric", F.when((F.col("m") < 2) | (F.col("mass") == 0), 1.0).otherwise(-F.col("s") / F.ln("m")).alias("e"))


def entropy_weights(scaled: DataFrame) -> DataFrame:
    """metric, e, d, w; equal weights where nothing differs."""
    d = metric_entropy(scaled).withColumn("d", 1 - F.col("e"))
    every = Window.partitionBy()  # one row for each metric
    total = F.sum("d").over(every)
    return d.withColumn("w", F.when(F.abs(total) > 1e-15, F.col("d") / total).otherwise(1.0 / F.count(F.lit(1)).over(every)))


def weighted_score(scaled: DataFrame, weights: DataFrame) -> DataFrame:
    return scaled.join(F.broadcast(weights.select("metric", "w")), "metric").groupBy("model_id").agg(F.sum(F.col("w") * F.col("x")).alias("score"))


def two_stage_rank(long: DataFrame, family_of: Column, norm: str = "minmax", cost: tuple[str, ...] = ()) -> DataFrame:
    """model_id, one score for each family, overall: families first, then the same rule on the family scores."""
    scaled = scale_metrics(long, norm, cost).withColumn("family", family_of)
    w = Window.partitionBy("family", "metric")
    p = scaled.withColumn("p", F.try_divide("x", F.sum("x").over(w)))
    e = p.groupBy("family", "metric").agg((-F.sum(F.when(F.col("p") > 0, F.col("p") * F.ln("p")).otherwise(0.0))).alias("s"), F.count(F.lit(1)).alias("m"), F.sum("x").alias("mass"))
    d = e.select("family", "metric", (1 - F.when((F.col("m") < 2) | (F.col("mass") == 0), 1.0).otherwise(F.col("s") / F.ln("m"))).alias("d"))
    inside = Window.partitionBy("family")
    total = F.sum("d").over(inside)
    weights = d.withColumn("w", F.when(F.abs(total) > 1e-15, F.col("d") / total).otherwise(1.0 / F.count(F.lit(1)).over(inside))).select("family", "metric", "w")
    first = scaled.join(F.broadcast(weights), ["family", "metric"]).groupBy("model_id", "family").agg(F.sum(F.col("w") * F.col("x")).alias("value"))
    second = scale_metrics(first.select("model_id", F.col("family").alias("metric"), "value"), norm)
    overall = weighted_score(second, entropy_weights(second)).withColumnRenamed("score", "overall")
    wide = first.groupBy("model_id").pivot("family", ["concept", "syntax", "schema"]).agg(F.first("value"))
    return wide.join(overall, "model_id")


def ranks(table: DataFrame, values: list[str]) -> DataFrame:
    """rank_{value} for each value, best first; ties share a rank."""
    return table.withColumns({f"rank_{v}": F.rank().over(Window.orderBy(F.desc(F.round(v, 9)))) for v in values})


def score_distribution(long: DataFrame) -> DataFrame:
    """metric, mean, sd, skew (population moments)."""
    w = Window.partitionBy("metric")
    dev = F.col("value") - F.avg("value").over(w)
    out = long.withColumn("dev", dev).groupBy("metric").agg(F.avg("value").alias("mean"), F.sqrt(F.avg(F.col("dev") ** 2)).alias("sd"), F.avg(F.col("dev") ** 3).alias("m3"))
    return out.select("metric", "mean", "sd", F.try_divide("m3", F.col("sd") ** 3).alias("skew"))


def score_histogram(long: DataFrame, bins: int = 10) -> DataFrame:
    """metric, bin, n over [0, 1] in equal bins; 1.0 belongs to the last."""
    at = F.least(F.lit(bins - 1), F.floor(F.col("value") * bins)).cast("int")
    return long.groupBy("metric", at.alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def kendall_tau(table: DataFrame, a: str, b: str) -> DataFrame:
    """tau of two rankings of the contestants (pairs of a bounded table)."""
    x, y = table.alias("x"), table.alias("y")
    sign = F.signum(F.col(f"x.{a}") - F.col(f"y.{a}")) * F.signum(F.col(f"x.{b}") - F.col(f"y.{b}"))
    return x.join(y, F.col("x.model_id") < F.col("y.model_id")).agg((F.sum(sign) / F.count(F.lit(1))).alias("tau"))


def pareto_front(table: DataFrame, gain: str, cost: str) -> DataFrame:
    """on_front: no other contestant is as good in both and better in one."""
    other = table.select(F.col(gain).alias("g2"), F.col(cost).alias("c2"))
    beats = (F.col("g2") >= F.col(gain)) & (F.col("c2") <= F.col(cost)) & ((F.col("g2") > F.col(gain)) | (F.col("c2") < F.col(cost)))
    front = table.join(F.broadcast(other), beats, "left_anti").select("model_id", F.lit(1).alias("on_front"))
    return table.join(F.broadcast(front), "model_id", "left").withColumn("on_front", F.coalesce("on_front", F.lit(0)))
