"""Accuracy, pass rates, repeated runs and robustness."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from querygrade.operators import measures as m
from querygrade.plans.fixtures import SUBTASKS, attempts, roster, with_ctes
from querygrade.queries import query, rounded
from querygrade.sources.tables import table

QUESTION = ["qid", "variant"]


def _concept(spark, sf):
    return attempts(spark, sf).where("family = 'concept'")


def _sql_attempts(spark, sf):
    return attempts(spark, sf).where("family <> 'concept'")


_PIVOT = ", ".join(f"avg(CASE WHEN subtask = '{s}' THEN CAST(answer = truth AS INTEGER) END) AS {s}" for s in SUBTASKS)
_CONCEPT = f"WITH per AS (SELECT model_id, {_PIVOT} FROM attempts WHERE family = 'concept' GROUP BY 1)"
_AVERAGE = "(" + " + ".join(SUBTASKS) + f") / {len(SUBTASKS)}"
_ROUND = ", ".join(f"round({s}, 6) AS {s}" for s in SUBTASKS)


@query("concept_accuracy", with_ctes(f"{_CONCEPT} SELECT model_id, {_ROUND}, round({_AVERAGE}, 6) AS average FROM per"))
def concept_accuracy(spark, sf):
    return rounded(m.concept_table(_concept(spark, sf), ["model_id"], SUBTASKS), *SUBTASKS, "average")


_MEANS = ", ".join(f"round(avg({s}), 6) AS {s}" for s in SUBTASKS)


@query("concept_by_category", with_ctes(f"{_CONCEPT} SELECT category, {_MEANS}, round(avg({_AVERAGE}), 6) AS average FROM per JOIN roster USING (model_id) GROUP BY 1"))
def concept_by_category(spark, sf):
    per = m.concept_table(_concept(spark, sf), ["model_id"], SUBTASKS)
    return rounded(m.category_means(per, roster(spark, sf), [*SUBTASKS, "average"]), *SUBTASKS, "average")


@query("concept_lenient", with_ctes("SELECT model_id, subtask, round(avg(CAST(upper(trim(answer)) = truth AS INTEGER)), 6) AS accuracy FROM attempts WHERE family = 'concept' GROUP BY 1, 2"))
def concept_lenient(spark, sf):
    return rounded(m.concept_accuracy(_concept(spark, sf), ["model_id"], lenient=True), "accuracy")


@query("concept_average_weighted", with_ctes("SELECT model_id, round(avg(CAST(answer = truth AS INTEGER)), 6) AS accuracy FROM attempts WHERE family = 'concept' GROUP BY 1"))
def concept_average_weighted(spark, sf):
    log = _concept(spark, sf).withColumn("hit", (F.col("answer") == F.col("truth")).cast("int"))
    return rounded(m.accuracy(log, ["model_id"], "hit"), "accuracy")


@query("invalid_rate", with_ctes("SELECT model_id, round(avg(CAST(NOT regexp_matches(answer, '^([A-D]|True|False)$') AS INTEGER)), 6) AS invalid FROM attempts WHERE family = 'concept' GROUP BY 1"))
def invalid_rate(spark, sf):
    return rounded(m.invalid_rate(_concept(spark, sf), ["model_id"]), "invalid")


@query("pass_rates", with_ctes("SELECT model_id, family, round(avg(exec_state), 6) AS epr, round(avg(syntax_state), 6) AS sa, round(avg(syntax_state) - avg(exec_state), 6) AS gap FROM attempts WHERE family <> 'concept' GROUP BY 1, 2"))
def pass_rates(spark, sf):
    return rounded(m.pass_rates(_sql_attempts(spark, sf), ["model_id", "family"]), "epr", "sa", "gap")


@query("exec_implies_syntax", with_ctes("SELECT count(*) AS violations FROM attempts WHERE exec_state > syntax_state"))
def exec_implies_syntax(spark, sf):
    return attempts(spark, sf).agg(F.count_if(F.col("exec_state") > F.col("syntax_state")).alias("violations"))


@query(
    "accuracy_rings",
    with_ctes(
        "SELECT model_id, round(avg(correct), 6) AS acc_all, round(avg(CASE WHEN result_kind = 'geometry' THEN correct END), 6) AS acc_geo, "
        "round(avg(CASE WHEN result_kind <> 'geometry' THEN correct END), 6) AS acc_other FROM attempts WHERE family <> 'concept' GROUP BY 1"
    ),
)
def accuracy_rings(spark, sf):
    return rounded(m.accuracy_by_kind(_sql_attempts(spark, sf), ["model_id"]), "acc_all", "acc_geo", "acc_other")


_PREFIX = "WITH flags AS (SELECT model_id, family, qid, variant, " + ", ".join(f"max(CASE WHEN run <= {n} THEN correct ELSE 0 END) AS f{n}" for n in (1, 3, 5)) + " FROM attempts WHERE family <> 'concept' GROUP BY 1, 2, 3, 4), passed AS (SELECT model_id, family, avg(f1) AS p1, avg(f3) AS p3, avg(f5) AS p5 FROM flags GROUP BY 1, 2)"


@query("pass_at_n", with_ctes(f"{_PREFIX} SELECT model_id, family, round(p1, 6) AS p1, round(p3, 6) AS p3, round(p5, 6) AS p5, round(p3 - p1, 6) AS d3, round(p5 - p3, 6) AS d5 FROM passed"))
def pass_at_n(spark, sf):
    return rounded(m.pass_gains(m.pass_at(_sql_attempts(spark, sf), ["model_id", "family"], QUESTION)), "p1", "p3", "p5", "d3", "d5")


_ESTIMATE = "WITH t AS (SELECT model_id, family, qid, variant, count(*) AS r, CAST(count(*) - sum(correct) AS DOUBLE) AS w, sum(correct) FILTER (WHERE run <= 1) AS c1, sum(correct) FILTER (WHERE run <= 3) AS c3, sum(correct) FILTER (WHERE run <= 5) AS c5 FROM attempts WHERE family <> 'concept' GROUP BY 1, 2, 3, 4)"


def _estimate(n: int) -> str:
    return "1 - " + " * ".join(f"greatest(w - {k}, 0) / (r - {k})" for k in range(n))


@query("pass_at_n_estimator", with_ctes(f"{_ESTIMATE} SELECT model_id, family, " + ", ".join(f"round(avg({_estimate(n)}), 6) AS p{n}" for n in (1, 3, 5)) + " FROM t GROUP BY 1, 2"))
def pass_at_n_estimator(spark, sf):
    return rounded(m.pass_at(_sql_attempts(spark, sf), ["model_id", "family"], QUESTION, mode="estimator"), "p1", "p3", "p5")


@query("pass_at_n_literal", with_ctes(f"{_ESTIMATE} SELECT model_id, family, " + ", ".join(f"round(avg(1 - c{n} / {n}.0), 6) AS p{n}" for n in (1, 3, 5)) + " FROM t GROUP BY 1, 2"))
def pass_at_n_literal(spark, sf):
    return rounded(m.pass_at(_sql_attempts(spark, sf), ["model_id", "family"], QUESTION, mode="literal"), "p1", "p3", "p5")


@query(
    "pass_at_n_sparse",
    """WITH log AS (SELECT s_nationkey, l_partkey, l_linenumber AS run, max(CAST(l_returnflag = 'R' OR l_linestatus = 'F' AS INTEGER)) AS correct
       FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE l_linenumber <= 5 GROUP BY 1, 2, 3),
    f AS (SELECT s_nationkey, l_partkey, max(CASE WHEN run <= 1 THEN correct ELSE 0 END) AS f1, max(CASE WHEN run <= 3 THEN correct ELSE 0 END) AS f3, max(correct) AS f5 FROM log GROUP BY 1, 2)
    SELECT s_nationkey, round(avg(f1), 6) AS p1, round(avg(f3), 6) AS p3, round(avg(f5), 6) AS p5 FROM f GROUP BY 1""",
)
def pass_at_n_sparse(spark, sf):
    items = table(spark, sf, "lineitem").where("l_linenumber <= 5").join(table(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    log = items.select("s_nationkey", "l_partkey", F.col("l_linenumber").alias("run"), ((F.col("l_returnflag") == "R") | (F.col("l_linestatus") == "F")).cast("int").alias("correct"))
    clean = m.clean_runs(log, ["s_nationkey", "l_partkey"])
    return rounded(m.pass_at(clean, ["s_nationkey"], ["l_partkey"]), "p1", "p3", "p5")


STABLE = f"{_PREFIX}, runs AS (SELECT model_id, family, run, avg(correct) AS a FROM attempts WHERE family <> 'concept' GROUP BY 1, 2, 3), cvs AS (SELECT model_id, family, stddev_pop(a) / nullif(avg(a), 0) AS cv FROM runs GROUP BY 1, 2)"


@query("stability", with_ctes(f"{STABLE} SELECT model_id, family, round(p5, 6) AS p5, round(cv, 6) AS cv, round(p5 / (1 + cv), 6) AS saa FROM passed JOIN cvs USING (model_id, family)"))
def stability(spark, sf):
    return rounded(m.stability(_sql_attempts(spark, sf), ["model_id", "family"], QUESTION), "p5", "cv", "saa")


@query("stability_sample_sd", with_ctes("WITH runs AS (SELECT model_id, run, avg(correct) AS a FROM attempts WHERE family <> 'concept' GROUP BY 1, 2) SELECT model_id, round(stddev_samp(a) / nullif(avg(a), 0), 6) AS cv FROM runs GROUP BY 1"))
def stability_sample_sd(spark, sf):
    return rounded(m.run_cv(_sql_attempts(spark, sf), ["model_id"], ddof=1), "cv")


@query(
    "robustness",
    with_ctes(
        "WITH b AS (SELECT model_id, family, avg(CASE WHEN variant = 0 THEN correct END) AS e, avg(CASE WHEN variant = 1 THEN correct END) AS n FROM attempts WHERE family <> 'concept' GROUP BY 1, 2) "
        'SELECT model_id, family, round(e, 6) AS explicit, round(n, 6) AS underspecified, round(e - n, 6) AS "drop", round((e - n) / nullif(e, 0), 6) AS relative_drop FROM b'
    ),
)
def robustness(spark, sf):
    return rounded(m.robustness(_sql_attempts(spark, sf), ["model_id", "family"]), "explicit", "underspecified", "drop", "relative_drop")


@query("category_means", with_ctes(f"{_PREFIX} SELECT category, round(avg(p1), 6) AS p1, round(avg(p3), 6) AS p3, round(avg(p5), 6) AS p5 FROM passed JOIN roster USING (model_id) GROUP BY 1"))
def category_means(spark, sf):
    return rounded(m.category_means(m.pass_at(_sql_attempts(spark, sf), ["model_id", "family"], QUESTION), roster(spark, sf), ["p1", "p3", "p5"]), "p1", "p3", "p5")


@query(
    "run_agreement",
    with_ctes(
        "WITH e AS (SELECT model_id, qid, variant, answer, count(*) AS n FROM attempts WHERE family <> 'concept' GROUP BY 1, 2, 3, 4), q AS (SELECT model_id, qid, variant, max(n) / sum(n) AS modal, count(*) AS kinds FROM e GROUP BY 1, 2, 3) "
        "SELECT model_id, round(avg(modal), 6) AS modal_share, round(avg(kinds), 6) AS distinct_answers FROM q GROUP BY 1"
    ),
)
def run_agreement(spark, sf):
    return rounded(m.run_agreement(_sql_attempts(spark, sf), ["model_id"], QUESTION), "modal_share", "distinct_answers")


@query("function_profile", with_ctes("SELECT func_id, round(avg(correct), 6) AS accuracy, count(*) AS n FROM attempts WHERE family <> 'concept' GROUP BY 1"))
def function_profile(spark, sf):
    return rounded(_sql_attempts(spark, sf).groupBy("func_id").agg(F.avg(F.col("correct").cast("double")).alias("accuracy"), F.count(F.lit(1)).alias("n")), "accuracy")


@query("accuracy_interval", with_ctes("WITH h AS (SELECT model_id, sum(correct) / count(*) AS p, count(*) AS n FROM attempts GROUP BY 1) SELECT model_id, round((p + 1.959964^2 / (2 * n) - 1.959964 * sqrt(p * (1 - p) / n + 1.959964^2 / (4.0 * n * n))) / (1 + 1.959964^2 / n), 6) AS low, round((p + 1.959964^2 / (2 * n) + 1.959964 * sqrt(p * (1 - p) / n + 1.959964^2 / (4.0 * n * n))) / (1 + 1.959964^2 / n), 6) AS high FROM h"))
def accuracy_interval(spark, sf):
    low, high = m.wilson(F.sum("correct"), F.count(F.lit(1)))
    return rounded(attempts(spark, sf).groupBy("model_id").agg(low.alias("low"), high.alias("high")), "low", "high")


@query("scale_trend", with_ctes("WITH h AS (SELECT model_id, category, avg(correct) AS a FROM attempts WHERE family <> 'concept' GROUP BY 1, 2), k AS (SELECT *, row_number() OVER (PARTITION BY category ORDER BY model_id) AS size FROM h) SELECT category, count(*) AS n, round(corr(size, a), 6) AS trend FROM k GROUP BY 1"))
def scale_trend(spark, sf):
    """Accuracy against the order of size inside a family of contestants."""
    each = m.accuracy(_sql_attempts(spark, sf), ["model_id"], name="a").join(roster(spark, sf).select("model_id", "category"), "model_id")
    sized = each.withColumn("size", F.row_number().over(Window.partitionBy("category").orderBy("model_id")))
    return rounded(sized.groupBy("category").agg(F.count(F.lit(1)).alias("n"), F.corr("size", "a").alias("trend")), "trend")


@query("bootstrap_difference")
def bootstrap_difference(spark, sf):
    return m.bootstrap_difference(_sql_attempts(spark, sf), 24, 12)


@query("missing_attempts", with_ctes("SELECT count(*) AS expected, 0 AS missing FROM attempts"))
def missing_attempts(spark, sf):
    log = attempts(spark, sf)
    grid = log.select("qid", "variant").distinct().crossJoin(F.broadcast(roster(spark, sf).select("model_id"))).withColumn("run", F.explode(F.sequence(F.lit(1), F.lit(5))))
    gone = grid.join(log, ["model_id", "qid", "variant", "run"], "left_anti").withColumn("gone", F.lit(1))
    return grid.join(gone, ["model_id", "qid", "variant", "run"], "left").agg(F.count(F.lit(1)).alias("expected"), F.count("gone").cast("int").alias("missing"))
