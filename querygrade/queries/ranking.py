"""Entropy weights, two-stage ranking, baselines and score shapes."""

from __future__ import annotations

from pyspark.sql import functions as F

from querygrade.operators import measures as m
from querygrade.operators import ranking as r
from querygrade.plans.fixtures import SUBTASKS, attempts, with_ctes
from querygrade.queries import query, rounded
from querygrade.sources.tables import written

MEASURES = ("epr", "sa", "acc", "p5", "robust")


def metric_table(spark, sf):
    """model_id and one column for each measure: concept_*, syntax_*, schema_*.

    The log is built and aggregated once, by question and then by contestant; the few hundred sums are written, and all
    that ranks contestants reads these.
    """
    log = attempts(spark, sf)
    right = (F.col("answer") == F.col("truth")).cast("long")
    total = {"n": F.count(F.lit(1)), "epr": F.sum("exec_state"), "sa": F.sum("syntax_state"), "acc": F.sum("correct"), "p5": F.max("correct"), "hit": F.sum(F.coalesce(right, F.lit(0)))}
    by = ["model_id", "family", "subtask", "variant"]
    asked = log.groupBy(*by, "qid").agg(*[c.alias(k) for k, c in total.items()])
    sums = written(asked.groupBy(*by).agg(F.count(F.lit(1)).alias("asked"), *[F.sum(k).alias(k) for k in total]), "fact-sums")

    def ratio(value, of, *cond):
        met = F.lit(True)
        for c in cond:
            met = met & c
        return F.sum(F.when(met, F.col(value)).cast("double")) / F.sum(F.when(met, F.col(of)).cast("double"))

    family, variant = F.col("family"), F.col("variant")
    out = [ratio("hit", "n", family == "concept", F.col("subtask") == s).alias(f"concept_{s}") for s in SUBTASKS]
    for name in ("syntax", "schema"):
        out += [ratio(k, "n", family == name).alias(f"{name}_{k}") for k in ("epr", "sa", "acc")]
        out += [ratio("p5", "asked", family == name).alias(f"{name}_p5"), ratio("acc", "n", family == name, variant == 1).alias(f"{name}_robust")]
    return sums.groupBy("model_id").agg(*out)


METRICS = [f"concept_{s}" for s in SUBTASKS] + [f"{f}_{x}" for f in ("syntax", "schema") for x in MEASURES]


def long_table(spark, sf):
    return r.long_metrics(metric_table(spark, sf), METRICS)


def _family():
    return F.regexp_extract("metric", "^([a-z]+)_", 1)


_LONG = (
    "WITH q AS (SELECT model_id, family, qid, variant, max(correct) AS f5 FROM attempts WHERE family <> 'concept' GROUP BY 1, 2, 3, 4), long AS ("
    + " UNION ALL ".join(f"SELECT model_id, 'concept_{s}' AS metric, avg(CAST(answer = truth AS INTEGER)) AS value FROM attempts WHERE family = 'concept' AND subtask = '{s}' GROUP BY 1" for s in SUBTASKS)
    + "".join(
        f" UNION ALL SELECT model_id, family || '_{name}', {value} FROM attempts WHERE family <> 'concept'{more} GROUP BY model_id, family"
        for name, value, more in (("epr", "avg(exec_state)", ""), ("sa", "avg(syntax_state)", ""), ("acc", "avg(correct)", ""), ("robust", "avg(correct)", " AND variant = 1"))
    )
    + " UNION ALL SELECT model_id, family || '_p5', avg(f5) FROM q GROUP BY model_id, family), "
    "scaled AS (SELECT model_id, metric, split_part(metric, '_', 1) AS family, coalesce((value - min(value) OVER w) / nullif(max(value) OVER w - min(value) OVER w, 0), 0) AS x FROM long WINDOW w AS (PARTITION BY metric)), "
    "p AS (SELECT *, x / nullif(sum(x) OVER (PARTITION BY metric), 0) AS p FROM scaled), "
    "ent AS (SELECT family, metric, CASE WHEN count(*) < 2 OR sum(x) = 0 THEN 1 ELSE -sum(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END) / ln(count(*)) END AS e FROM p GROUP BY 1, 2)"
)
_STAGES = (
    _LONG + ", w1 AS (SELECT family, metric, (1 - e) / sum(1 - e) OVER (PARTITION BY family) AS w FROM ent), "
    "fam AS (SELECT model_id, s.family, sum(w * x) AS score FROM scaled s JOIN w1 USING (family, metric) GROUP BY 1, 2), "
    "s2 AS (SELECT model_id, family, coalesce((score - min(score) OVER w) / nullif(max(score) OVER w - min(score) OVER w, 0), 0) AS x FROM fam WINDOW w AS (PARTITION BY family)), "
    "p2 AS (SELECT *, x / nullif(sum(x) OVER (PARTITION BY family), 0) AS p FROM s2), "
    "e2 AS (SELECT family, 1 + sum(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END) / ln(count(*)) AS d FROM p2 GROUP BY 1), "
    "w2 AS (SELECT family, d / sum(d) OVER () AS w FROM e2), "
    "total AS (SELECT model_id, sum(w * x) AS overall FROM s2 JOIN w2 USING (family) GROUP BY 1), "
    "board AS (SELECT model_id, max(score) FILTER (WHERE family = 'concept') AS concept, max(score) FILTER (WHERE family = 'syntax') AS syntax, max(score) FILTER (WHERE family = 'schema') AS schema, any_value(overall) AS overall FROM fam JOIN total USING (model_id) GROUP BY 1)"
)
DIMENSIONS = ["concept", "syntax", "schema", "overall"]


@query("entropy_weights", with_ctes(_LONG + " SELECT metric, round(e, 6) AS e, round(1 - e, 6) AS d, round((1 - e) / sum(1 - e) OVER (), 6) AS w FROM ent"))
def entropy_weights(spark, sf):
    return rounded(r.entropy_weights(r.scale_metrics(long_table(spark, sf))), "e", "d", "w")


_ROUNDED = ", ".join(f"round({d}, 6) AS {d}" for d in DIMENSIONS)


@query("overall_rank", with_ctes(_STAGES + f" SELECT model_id, {_ROUNDED}, CAST(rank() OVER (ORDER BY round(overall, 9) DESC) AS INTEGER) AS rank_overall FROM board"))
def overall_rank(spark, sf):
    return rounded(r.ranks(r.two_stage_rank(long_table(spark, sf), _family()), ["overall"]), *DIMENSIONS)


@query("rank_heatmap", with_ctes(_STAGES + " SELECT model_id, " + ", ".join(f"CAST(rank() OVER (ORDER BY round({d}, 9) DESC) AS INTEGER) AS rank_{d}" for d in DIMENSIONS) + " FROM board"))
def rank_heatmap(spark, sf):
    return r.ranks(r.two_stage_rank(long_table(spark, sf), _family()), DIMENSIONS).select("model_id", *[f"rank_{d}" for d in DIMENSIONS])


_BOARD_LONG = _STAGES + ", bl AS (" + " UNION ALL ".join(f"SELECT model_id, '{d}' AS metric, {d} AS value FROM board" for d in DIMENSIONS) + ")"


@query("score_distribution", with_ctes(_BOARD_LONG + ", c AS (SELECT *, value - avg(value) OVER (PARTITION BY metric) AS dev FROM bl) SELECT metric, round(avg(value), 6) AS mean, round(sqrt(avg(dev^2)), 6) AS sd, round(avg(dev^3) / sqrt(avg(dev^2))^3, 6) AS skew FROM c GROUP BY 1"))
def score_distribution(spark, sf):
    return rounded(r.score_distribution(r.long_metrics(r.two_stage_rank(long_table(spark, sf), _family()), DIMENSIONS)), "mean", "sd", "skew")


@query("score_histogram", with_ctes(_BOARD_LONG + " SELECT metric, CAST(least(9, floor(round(value, 9) * 10)) AS INTEGER) AS bin, count(*) AS n FROM bl GROUP BY 1, 2"))
def score_histogram(spark, sf):
    long = r.long_metrics(r.two_stage_rank(long_table(spark, sf), _family()), DIMENSIONS)
    return r.score_histogram(long.withColumn("value", F.round("value", 9)))


@query("baseline_rank_distance", with_ctes(_STAGES + ", base AS (SELECT model_id, round(avg(value), 9) AS plain FROM long GROUP BY 1), b AS (SELECT model_id, round(overall, 9) AS overall, plain, round((concept + syntax + schema) / 3, 9) AS equal FROM board JOIN base USING (model_id)) SELECT 'unweighted' AS baseline, round(avg(sign(x.overall - y.overall) * sign(x.plain - y.plain)), 6) AS tau FROM b x JOIN b y ON x.model_id < y.model_id UNION ALL SELECT 'equal_families', round(avg(sign(x.overall - y.overall) * sign(x.equal - y.equal)), 6) FROM b x JOIN b y ON x.model_id < y.model_id"))
def baseline_rank_distance(spark, sf):
    long = long_table(spark, sf)
    plain = long.groupBy("model_id").agg(F.round(F.avg("value"), 9).alias("plain"))
    board = r.two_stage_rank(long, _family()).join(plain, "model_id").withColumns({"overall": F.round("overall", 9), "equal": F.round((F.col("concept") + F.col("syntax") + F.col("schema")) / 3, 9)})
    both = [r.kendall_tau(board, "overall", b).withColumn("baseline", F.lit(n)) for n, b in (("unweighted", "plain"), ("equal_families", "equal"))]
    return rounded(both[0].unionByName(both[1]), "tau")


@query("metric_correlation", with_ctes(_LONG + ", v AS (SELECT model_id, max(value) FILTER (WHERE metric = 'syntax_sa') AS sa, max(value) FILTER (WHERE metric = 'syntax_epr') AS epr, max(value) FILTER (WHERE metric = 'syntax_acc') AS acc FROM long GROUP BY 1), k AS (SELECT *, rank() OVER (ORDER BY sa) + (count(*) OVER (PARTITION BY sa) - 1) / 2.0 AS rs, rank() OVER (ORDER BY epr) + (count(*) OVER (PARTITION BY epr) - 1) / 2.0 AS re, rank() OVER (ORDER BY acc) + (count(*) OVER (PARTITION BY acc) - 1) / 2.0 AS ra FROM v) SELECT 'syntax_sa~syntax_epr' AS pair, round(corr(sa, epr), 6) AS pearson, round(corr(rs, re), 6) AS spearman FROM k UNION ALL SELECT 'syntax_acc~syntax_epr', round(corr(acc, epr), 6), round(corr(ra, re), 6) FROM k"))
def metric_correlation(spark, sf):
    return rounded(m.metric_correlation(metric_table(spark, sf), [("syntax_sa", "syntax_epr"), ("syntax_acc", "syntax_epr")]), "pearson", "spearman")


for _norm, _x in (("max", "coalesce(value / nullif(max(value) OVER w, 0), 0)"), ("sum", "coalesce(value / nullif(sum(value) OVER w, 0), 0)"), ("none", "value")):

    def _scaled(spark, sf, norm=_norm):
        return rounded(r.scale_metrics(long_table(spark, sf), norm), "x")

    query(f"scale_{_norm}", with_ctes(_LONG + f" SELECT model_id, metric, round({_x}, 6) AS x FROM long WINDOW w AS (PARTITION BY metric)"))(_scaled)
