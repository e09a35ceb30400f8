"""Measures over answer logs: one aggregation each, keyed by any columns (``by``)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from querygrade.functions.units import share


def mean_of(flag: Column) -> Column:
    return F.avg(flag.cast("double"))


def concept_accuracy(log: DataFrame, by: list[str], lenient: bool = False) -> DataFrame:
    """by..., subtask, accuracy: exact equality of answer and key; lenient trims and ignores case."""
    got, key = (F.upper(F.trim("answer")), F.upper(F.trim("truth"))) if lenient else (F.col("answer"), F.col("truth"))
    return log.groupBy(*by, "subtask").agg(mean_of(F.coalesce(got == key, F.lit(False))).alias("accuracy"))


def concept_table(log: DataFrame, by: list[str], subtasks: tuple[str, ...]) -> DataFrame:
    """One column for each subtask and their unweighted mean."""
    wide = concept_accuracy(log, by).groupBy(*by).pivot("subtask", list(subtasks)).agg(F.first("accuracy"))
    return wide.withColumn("average", sum((F.col(s) for s in subtasks[1:]), F.col(subtasks[0])) / len(subtasks))


def invalid_rate(log: DataFrame, by: list[str], valid: str = "^([A-D]|True|False)$") -> DataFrame:
    return log.groupBy(*by).agg(mean_of(~F.coalesce(F.col("answer").rlike(valid), F.lit(False))).alias("invalid"))


def pass_rates(log: DataFrame, by: list[str]) -> DataFrame:
    """epr (statements that execute), sa (statements that parse) and their gap."""
    rates = log.groupBy(*by).agg(mean_of(F.col("exec_state")).alias("epr"), mean_of(F.col("syntax_state")).alias("sa"))
    return rates.withColumn("gap", F.col("sa") - F.col("epr"))


def accuracy(log: DataFrame, by: list[str], right: str = "correct", name: str = "accuracy") -> DataFrame:
    return log.groupBy(*by).agg(mean_of(F.col(right)).alias(name))


def accuracy_by_kind(log: DataFrame, by: list[str]) -> DataFrame:
    """Accuracy of all questions, of geometry results and of the others."""
    geo = F.col("result_kind") == "geometry"
    return log.groupBy(*by).agg(mean_of(F.col("correct")).alias("acc_all"), F.avg(F.when(geo, F.col("correct").cast("double"))).alias("acc_geo"), F.avg(F.when(~geo, F.col("correct").cast("double"))).alias("acc_other"))


def clean_runs(log: DataFrame, question: list[str], latest: Column | None = None) -> DataFrame:
    """One row for each question and run; of repeated rows the latest, or the right one if none is later."""
    order = F.max(F.struct((latest if latest is not None else F.lit(0)).alias("at"), F.col("correct").alias("correct")))
    return log.groupBy(*question, "run").agg(order.getField("correct").alias("correct"))


def pass_at(log: DataFrame, by: list[str], question: list[str], ns: tuple[int, ...] = (1, 3, 5), mode: str = "prefix", runs: int | None = None) -> DataFrame:
    """p{n} for every n, from one aggregation by question and one by ``by``.

    prefix: any of the first n runs is right.  estimator: 1 - C(wrong, n) / C(all, n), the unbiased form, null where fewer
    than n runs exist.  literal: 1 - (right in the first n) / n, as printed.
    """
    right = F.col("correct") == 1
    flags = {}
    for n in ns:
        first = F.col("run") <= n
        if mode == "prefix":
            flags[f"p{n}"] = F.max(F.when(first & right, 1.0).otherwise(0.0))
        elif mode == "literal":
            flags[f"p{n}"] = 1 - F.count_if(first & right) / F.lit(float(n))
        else:
            total, wrong = F.count(F.lit(1)), F.count_if(~right)
            miss = F.lit(1.0)
            for k in range(n):
                miss = miss * share(F.greatest(wrong - k, F.lit(0)), total - k)
            flags[f"p{n}"] = F.when(total >= n, 1 - miss)
    per_question = log.groupBy(*by, *[q for q in question if q not in by]).agg(*[c.alias(k) for k, c in flags.items()])
    return per_question.groupBy(*by).agg(*[F.avg(k).alias(k) for k in flags])


def pass_gains(table: DataFrame, ns: tuple[int, ...] = (1, 3, 5)) -> DataFrame:
    out = table
    for a, b in zip(ns, ns[1:], strict=False):
        out = out.withColumn(f"d{b}", F.col(f"p{b}") - F.col(f"p{a}"))
    return out


def run_cv(log: DataFrame, by: list[str], ddof: int = 0) -> DataFrame:
    """Coefficient of variation of the per-run accuracies; null where the mean is 0."""
    per_run = accuracy(log, [*by, "run"])
    spread = F.stddev_pop("accuracy") if ddof == 0 else F.stddev_samp("accuracy")
    return per_run.groupBy(*by).agg(share(spread, F.when(F.avg("accuracy") != 0, F.avg("accuracy"))).alias("cv"))


def stability(log: DataFrame, by: list[str], question: list[str]) -> DataFrame:
    """cv and saa = pass@5 / (1 + cv)."""
    best = pass_at(log, by, question, (5,))
    return best.join(run_cv(log, by), by).select(*by, "p5", "cv", (F.col("p5") / (1 + F.col("cv"))).alias("saa"))


def robustness(log: DataFrame, by: list[str]) -> DataFrame:
    """Accuracy with explicit and underspecified questions, absolute and relative drop."""
    both = log.groupBy(*by).agg(*[F.avg(F.when(F.col("variant") == v, F.col("correct").cast("double"))).alias(n) for v, n in ((0, "explicit"), (1, "underspecified"))])
    drop = F.col("explicit") - F.col("underspecified")
    return both.withColumns({"drop": drop, "relative_drop": F.try_divide(drop, F.col("explicit"))})


def run_agreement(log: DataFrame, by: list[str], question: list[str]) -> DataFrame:
    """Mean share of the most frequent answer of a question's runs, and mean number of distinct answers."""
    keys = [*by, *[q for q in question if q not in by]]
    each = log.groupBy(*keys, "answer").agg(F.count(F.lit(1)).alias("n"))
    per_question = each.groupBy(*keys).agg((F.max("n") / F.sum("n")).alias("modal"), F.count(F.lit(1)).alias("kinds"))
    return per_question.groupBy(*by).agg(F.avg("modal").alias("modal_share"), F.avg("kinds").alias("distinct_answers"))


def category_means(table: DataFrame, roster: DataFrame, values: list[str]) -> DataFrame:
    """Unweighted means over the contestants of a category."""
    return table.join(F.broadcast(roster.select("model_id", "category")), "model_id").groupBy("category").agg(*[F.avg(v).alias(v) for v in values])


def above_mean(table: DataFrame, values: list[str]) -> DataFrame:
    """Rows that are above the mean in every value (a table of one row for each contestant)."""
    w = Window.partitionBy()
    marked = table.withColumns({f"__{v}": F.col(v) > F.avg(v).over(w) for v in values})
    return marked.where(" AND ".join(f"__{v}" for v in values)).select(*table.columns)


def wilson(hits: Column, n: Column, z: float = 1.959964) -> tuple[Column, Column]:
    """Bounds of a share's confidence interval."""
    p, m = share(hits, n), n.cast("double")
    middle, half = p + z * z / (2 * m), z * F.sqrt(p * (1 - p) / m + z * z / (4 * m * m))
    return (middle - half) / (1 + z * z / m), (middle + half) / (1 + z * z / m)


def bootstrap_difference(log: DataFrame, first: int, second: int, draws: int = 200, seed: int = 1) -> DataFrame:
    """Paired bootstrap over questions of the difference of two contestants' accuracies: mean, lower and upper 95 % bound.

    A question's weight in a draw is Poisson(1), taken from a hash of question and draw, so no resampled
    copy of the log exists.
    """
    pair = log.where(F.col("model_id").isin(first, second)).groupBy("qid", "variant").agg(F.avg(F.when(F.col("model_id") == first, F.col("correct").cast("double"))).alias("a"), F.avg(F.when(F.col("model_id") == second, F.col("correct").cast("double"))).alias("b")).where("a is not null and b is not null")
    drawn = pair.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(draws))))
    point = (F.pmod(F.xxhash64("qid", "variant", "draw", F.lit(seed)), F.lit(1 << 30)) + 0.5) / (1 << 30)
    weight = sum((F.when(point > edge, 1).otherwise(0) for edge in (0.367879, 0.735759, 0.919699, 0.981012, 0.996340, 0.999406)), F.lit(0))
    each = drawn.withColumn("w", weight).groupBy("draw").agg(F.try_divide(F.sum(F.col("w") * (F.col("a") - F.col("b"))), F.sum("w")).alias("d"))
    return each.agg(F.avg("d").alias("difference"), F.percentile("d", 0.025).alias("low"), F.percentile("d", 0.975).alias("high"))


def metric_correlation(table: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """pair, pearson, spearman over the contestants' values (ties by average rank)."""

    def ranks(v: str) -> Column:
        low = F.rank().over(Window.orderBy(v))
        return low + (F.count(F.lit(1)).over(Window.partitionBy(v)) - 1) / 2.0

    names = sorted({v for p in pairs for v in p})
    ranked = table.withColumns({f"rank_{v}": ranks(v) for v in names})
    rows = F.array(*[F.struct(F.lit(f"{a}~{b}").alias("pair"), F.col(f"c{k}").alias("pearson"), F.col(f"s{k}").alias("spearman")) for k, (a, b) in enumerate(pairs)])
    out = ranked.agg(*[F.corr(a, b).alias(f"c{k}") for k, (a, b) in enumerate(pairs)], *[F.corr(f"rank_{a}", f"rank_{b}").alias(f"s{k}") for k, (a, b) in enumerate(pairs)])
    return out.select(F.inline(rows))
