"""Inputs of the grading methods, derived from the given tables; each with its DuckDB twin in ``CTES``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from querygrade.functions.units import sql_unit as u
from querygrade.functions.units import unit_of
from querygrade.sources.tables import spread, table

RUNS = 5
FAMILIES = ("concept", "syntax", "schema")
SUBTASKS = ("purpose", "parameter", "return_type", "rule")
KINDS = ("geometry", "number", "text", "boolean")


def _pick(names: tuple[str, ...], at: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, names)), (at + 1).cast("int"))


def roster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contestants with category."""
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    joined = nation.join(region, nation["n_regionkey"] == region["r_regionkey"])
    return joined.select(F.col("n_nationkey").alias("model_id"), F.col("n_name").alias("model_name"), F.col("n_regionkey").alias("category"), F.col("r_name").alias("category_name"))


def questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Questions of three families, each explicit (0) and underspecified (1)."""
    # each row becomes 250 attempts
    base = spread(table(spark, sf_dir, "part").select("p_partkey", "p_size", "p_brand", "p_name"))
    key, size = F.col("p_partkey"), F.col("p_size")
    return base.select(
        key.alias("qid"), F.explode(F.array(F.lit(0), F.lit(1))).alias("variant"), _pick(FAMILIES, key % 3).alias("family"), _pick(SUBTASKS, size % 4).alias("subtask"),
        F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int").alias("func_id"), _pick(KINDS, size % 4).alias("result_kind"), F.chr(65 + size % 4).alias("truth"), size.alias("size"), F.col("p_name").alias("name"),
    )


def attempts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every contestant's five runs of every question, with outcome, states, answer, tokens and seconds."""
    asked = questions(spark, sf_dir)
    # contestants are the rows of ``nation``: a fixed table, so the replication is by a bounded side
    rows = asked.crossJoin(F.broadcast(roster(spark, sf_dir))).withColumn("run", F.explode(F.sequence(F.lit(1), F.lit(RUNS))))
    key = F.concat_ws("-", "model_id", "qid", "variant", "run")
    hard = unit_of("q", F.col("qid")) % 1000
    noise = unit_of("r", key) % 400
    right = hard + noise - 200 + 150 * F.col("variant") < 250 + 20 * F.col("model_id")
    rows = rows.withColumns({"correct": right.cast("int"), "key": key})
    rows = rows.withColumn("syntax_state", F.when((F.col("correct") == 1) | (unit_of("s", F.col("key")) % 100 < 90), 1).otherwise(0))
    rows = rows.withColumn("exec_state", F.when((F.col("correct") == 1) | ((F.col("syntax_state") == 1) & (unit_of("e", F.col("key")) % 100 < 60)), 1).otherwise(0))
    wrong = F.chr(65 + (F.col("size") + 1 + unit_of("w", F.col("key")) % 3) % 4)
    answer = F.when(F.col("correct") == 1, F.col("truth")).otherwise(wrong)
    spoilt = unit_of("n", F.col("key")) % 20
    answer = F.when(spoilt == 0, F.concat(F.lower(answer), F.lit(" "))).when(spoilt == 1, F.lit("?")).otherwise(answer)
    return rows.withColumns({"answer": answer, "tokens": 50 + unit_of("t", F.col("key")) % 200, "seconds": (unit_of("z", F.col("key")) % 1000) / 100.0}).drop("key")


def _sql_case(names: tuple[str, ...], at: str) -> str:
    return "CASE " + at + "".join(f" WHEN {k} THEN '{n}'" for k, n in enumerate(names)) + " END"


_KEY = "model_id || '-' || qid || '-' || variant || '-' || run"
CTES = f"""
roster AS (SELECT n_nationkey AS model_id, n_name AS model_name, n_regionkey AS category, r_name AS category_name FROM nation JOIN region ON n_regionkey = r_regionkey),
questions AS (
  SELECT p_partkey AS qid, variant, {_sql_case(FAMILIES, "p_partkey % 3")} AS family, {_sql_case(SUBTASKS, "p_size % 4")} AS subtask,
         CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS INTEGER) AS func_id, {_sql_case(KINDS, "p_size % 4")} AS result_kind, chr(65 + p_size % 4) AS truth, p_size AS size, p_name AS name
  FROM part, (VALUES (0), (1)) v(variant)),
graded AS (
  SELECT *, CAST({u("'q' || qid")} % 1000 + {u("'r' || " + _KEY)} % 400 - 200 + 150 * variant < 250 + 20 * model_id AS INTEGER) AS correct
  FROM roster, questions, (VALUES (1), (2), (3), (4), (5)) r(run)),
parsed AS (SELECT *, CASE WHEN correct = 1 OR {u("'s' || " + _KEY)} % 100 < 90 THEN 1 ELSE 0 END AS syntax_state FROM graded),
attempts AS (
  SELECT *, CASE WHEN correct = 1 OR (syntax_state = 1 AND {u("'e' || " + _KEY)} % 100 < 60) THEN 1 ELSE 0 END AS exec_state,
         CASE WHEN {u("'n' || " + _KEY)} % 20 = 0 THEN lower(plain) || ' ' WHEN {u("'n' || " + _KEY)} % 20 = 1 THEN '?' ELSE plain END AS answer,
         50 + {u("'t' || " + _KEY)} % 200 AS tokens, ({u("'z' || " + _KEY)} % 1000) / 100.0 AS seconds
  FROM (SELECT *, CASE WHEN correct = 1 THEN truth ELSE chr(CAST(65 + (size + 1 + {u("'w' || " + _KEY)} % 3) % 4 AS INTEGER)) END AS plain FROM parsed))
"""


def with_ctes(body: str) -> str:
    """A DuckDB query over the derived inputs; ``body`` may begin with further named queries."""
    return f"WITH {CTES}{', ' + body.strip()[5:] if body.strip().startswith('WITH ') else body}"
