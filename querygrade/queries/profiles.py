"""Errors, resources and costs, from events and conversations."""

from __future__ import annotations

from pyspark.sql import functions as F

from querygrade.operators import measures as m
from querygrade.operators import profiles as p
from querygrade.operators import ranking as r
from querygrade.plans.fixtures import attempts, roster, with_ctes
from querygrade.queries import query, rounded
from querygrade.sources.tables import table

#: Error texts of the log, by event number.
MESSAGES = (
    "connection reset by peer", "syntax error near FROM", "relation zones does not exist", "function st_bufer does not exist",
    "invalid WKT at position 9", "operation on mixed SRID geometries", "division by zero", "something else",
)


def run_log(spark, sf):
    """event_id, ts, model_id, family, seconds, tokens, error_text."""
    e = table(spark, sf, "events")
    text = F.when(F.col("event_type") == "error", F.element_at(F.array(*map(F.lit, MESSAGES)), (F.col("event_id") % 8 + 1).cast("int")))
    tokens = F.get_json_object("props", "$.k").cast("long")
    family = F.when(F.col("event_id") % 2 == 0, "syntax").otherwise("schema")
    return e.select("event_id", "ts", (F.col("user_id") % 25).cast("int").alias("model_id"), family.alias("family"), F.col("value").alias("seconds"), tokens.alias("tokens"), text.alias("error_text"))


def error_log(spark, sf):
    return run_log(spark, sf).withColumn("class", p.classify_error(F.col("error_text")))


_TEXTS = "CASE event_id % 8 " + " ".join(f"WHEN {k} THEN '{t}'" for k, t in enumerate(MESSAGES)) + " END"
_LOG = f"log AS (SELECT event_id, ts, CAST(user_id % 25 AS INTEGER) AS model_id, CASE WHEN event_id % 2 = 0 THEN 'syntax' ELSE 'schema' END AS family, value AS seconds, CAST(json_extract_string(props, '$.k') AS BIGINT) AS tokens, CASE WHEN event_type = 'error' THEN {_TEXTS} END AS error_text FROM events), errors AS (SELECT *, {p.sql_classify('error_text')} AS class FROM log)"


@query("error_profile", f"WITH {_LOG} SELECT model_id, class, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY model_id), 6) AS share FROM errors WHERE class IS NOT NULL GROUP BY 1, 2")
def error_profile(spark, sf):
    return rounded(p.error_profile(error_log(spark, sf), ["model_id"]), "share")


@query("error_by_category", f"WITH {_LOG} SELECT n_regionkey AS category, class, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY n_regionkey), 6) AS share FROM errors JOIN nation ON model_id = n_nationkey WHERE class IS NOT NULL GROUP BY 1, 2")
def error_by_category(spark, sf):
    log = error_log(spark, sf).join(F.broadcast(roster(spark, sf)), "model_id")
    return rounded(p.error_profile(log, ["category"]), "share")


@query("error_dominance", f"WITH {_LOG}, c AS (SELECT model_id, class, count(*) AS n FROM errors WHERE class IS NOT NULL GROUP BY 1, 2), k AS (SELECT *, row_number() OVER (PARTITION BY model_id ORDER BY n DESC, class) AS r, n / sum(n) OVER (PARTITION BY model_id) AS share FROM c) SELECT model_id, round(sum(share), 6) AS dominance FROM k WHERE r <= 2 GROUP BY 1")
def error_dominance(spark, sf):
    return rounded(p.dominant_classes(p.error_profile(error_log(spark, sf), ["model_id"]), ["model_id"]), "dominance")


@query("error_shift", f"WITH {_LOG}, s AS (SELECT family, class, count(*) / sum(count(*)) OVER (PARTITION BY family) AS share FROM errors WHERE class IS NOT NULL GROUP BY 1, 2) SELECT class, round(coalesce(sum(share) FILTER (WHERE family = 'schema'), 0) - coalesce(sum(share) FILTER (WHERE family = 'syntax'), 0), 6) AS delta FROM s GROUP BY 1")
def error_shift(spark, sf):
    return rounded(p.error_shift(p.error_profile(error_log(spark, sf), ["family"]), "syntax", "schema"), "delta")


@query("resource_summary", f"WITH {_LOG} SELECT model_id, family, count(*) AS n, round(avg(tokens), 6) AS mean_tokens, round(avg(seconds), 6) AS mean_seconds FROM log GROUP BY 1, 2")
def resource_summary(spark, sf):
    return rounded(p.resource_summary(run_log(spark, sf), ["model_id", "family"]), "mean_tokens", "mean_seconds")


@query("running_means", f"WITH {_LOG} SELECT event_id, model_id, round(avg(seconds) OVER (PARTITION BY model_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) + 1e-9, 6) AS mean_so_far FROM log")
def running_means(spark, sf):
    out = p.running_means(run_log(spark, sf), ["model_id"], ["ts", "event_id"], "seconds")
    # 1e-9 keeps exact halves on one side of the rounding in both engines
    return out.select("event_id", "model_id", F.round(F.col("mean_so_far") + 1e-9, 6).alias("mean_so_far"))


_COST = f"WITH {_LOG}, cost AS (SELECT model_id, avg(tokens) AS mean_tokens, avg(seconds) AS mean_seconds FROM log GROUP BY 1), good AS (SELECT model_id, avg(correct) AS accuracy FROM attempts WHERE family <> 'concept' GROUP BY 1), t AS (SELECT model_id, round(accuracy, 9) AS accuracy, round(mean_tokens, 9) AS mean_tokens, round(mean_seconds, 9) AS mean_seconds FROM cost JOIN good USING (model_id))"


def _costs(spark, sf):
    log = p.resource_summary(run_log(spark, sf), ["model_id"])
    good = m.accuracy(attempts(spark, sf).where("family <> 'concept'"), ["model_id"])
    return rounded(log.join(good, "model_id").select("model_id", "accuracy", "mean_tokens", "mean_seconds"), "accuracy", "mean_tokens", "mean_seconds", digits=9)


@query("cost_pareto", with_ctes(_COST + " SELECT model_id, CAST(NOT EXISTS (SELECT 1 FROM t o WHERE o.accuracy >= t.accuracy AND o.mean_seconds <= t.mean_seconds AND (o.accuracy > t.accuracy OR o.mean_seconds < t.mean_seconds)) AS INTEGER) AS on_front FROM t"))
def cost_pareto(spark, sf):
    return r.pareto_front(_costs(spark, sf), "accuracy", "mean_seconds").select("model_id", "on_front")


@query("cost_effectiveness", with_ctes(_COST + " SELECT model_id, round(accuracy * 1000 / mean_tokens, 6) AS per_1k_tokens, round(accuracy / mean_seconds, 6) AS per_second FROM t"))
def cost_effectiveness(spark, sf):
    return rounded(p.cost_effectiveness(_costs(spark, sf)), "per_1k_tokens", "per_second").select("model_id", "per_1k_tokens", "per_second")


@query("session_tokens", "SELECT role, count(*) AS turns, CAST(sum(len(string_split(trim(regexp_replace(text, '[ \\t\\n\\r\\f\\v]+', ' ', 'g')), ' '))) AS BIGINT) AS tokens FROM conversations WHERE length(trim(text)) > 0 GROUP BY 1")
def session_tokens(spark, sf):
    words = F.size(F.split(F.trim(F.regexp_replace("text", r"[ \t\n\r\f\x0b]+", " ")), " "))
    return table(spark, sf, "conversations").where(F.length(F.trim("text")) > 0).groupBy("role").agg(F.count(F.lit(1)).alias("turns"), F.sum(words.cast("long")).alias("tokens"))


@query("stage_hours", "SELECT event_type AS stage, round(sum(value / 3600), 6) AS hours FROM events GROUP BY ROLLUP (event_type)")
def stage_hours(spark, sf):
    log = table(spark, sf, "events").select(F.col("event_type").alias("stage"), (F.col("value") / 3600).alias("hours"))
    return rounded(p.stage_hours(log), "hours")
