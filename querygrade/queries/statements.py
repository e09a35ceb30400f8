"""Structure scan, alignment measures, result comparison and execution."""

from __future__ import annotations

from pyspark.sql import functions as F

from querygrade.functions.units import norm_value
from querygrade.operators import alignment as a
from querygrade.operators import measures as m
from querygrade.operators.sandbox import execute_candidates, execute_cells, freeze_answers, graded
from querygrade.operators.values import value_verdict
from querygrade.plans.candidates import CATALOG, CTES, KINDS, REFERENCE, candidates, facts_by_question, references
from querygrade.plans.fixtures import with_ctes
from querygrade.queries import query, rounded
from querygrade.sources.tables import table


def _scored(spark, sf):
    return a.scored(candidates(spark, sf), CATALOG, REFERENCE)


def _c(body: str) -> str:
    return with_ctes(f"WITH {CTES}{body}")


def _text(column: str):
    return F.array_join(F.array_sort(column), ",")


@query("sql_structure", _c(" SELECT DISTINCT template, tables, fields, functions FROM candidates"))
def sql_structure(spark, sf):
    log = _scored(spark, sf)
    return log.select("template", _text("tables").alias("tables"), _text("fields").alias("fields"), F.array_join("functions", ",").alias("functions")).distinct()


@query("sql_syntax_state", _c(" SELECT template, count(*) AS n, CAST(sum(state) AS BIGINT) AS parsed FROM candidates GROUP BY 1"))
def sql_syntax_state(spark, sf):
    return _scored(spark, sf).groupBy("template").agg(F.count(F.lit(1)).alias("n"), F.sum("syntax_state").alias("parsed"))


@query("alignment_syntax", _c(" SELECT model_id, round(avg(fnr), 6) AS fnr, round(avg(ama), 6) AS ama FROM candidates WHERE family = 'syntax' GROUP BY 1"))
def alignment_syntax(spark, sf):
    return rounded(_scored(spark, sf).where("family = 'syntax'").groupBy("model_id").agg(F.avg("fnr").alias("fnr"), F.avg("ama").alias("ama")), "fnr", "ama")


_SCHEMA = "SELECT model_id, avg(thr) AS thr, avg(fhr) AS fhr, avg(fnr) AS fnr FROM candidates WHERE family = 'schema' GROUP BY 1"


@query("alignment_schema", _c(f", s AS ({_SCHEMA}) SELECT model_id, round(thr, 6) AS thr, round(fhr, 6) AS fhr, round(fnr, 6) AS fnr FROM s"))
def alignment_schema(spark, sf):
    return rounded(_schema(spark, sf), "thr", "fhr", "fnr")


def _schema(spark, sf):
    return _scored(spark, sf).where("family = 'schema'").groupBy("model_id").agg(*[F.avg(c).alias(c) for c in ("thr", "fhr", "fnr")])


@query("above_mean_panel", _c(f", s AS (SELECT model_id, round(thr, 9) AS thr, round(fhr, 9) AS fhr, round(fnr, 9) AS fnr FROM ({_SCHEMA})) SELECT model_id FROM s WHERE thr > (SELECT avg(thr) FROM s) AND fhr > (SELECT avg(fhr) FROM s) AND fnr > (SELECT avg(fnr) FROM s)"))
def above_mean_panel(spark, sf):
    return m.above_mean(rounded(_schema(spark, sf), "thr", "fhr", "fnr", digits=9), ["thr", "fhr", "fnr"]).select("model_id")


@query("alignment_denominators", _c(", h AS (SELECT *, CASE WHEN tables = '' THEN 0 ELSE len(string_split(tables, ',')) END AS got FROM candidates) SELECT model_id, round(avg(thr), 6) AS precision, round(avg(thr * got / 2), 6) AS recall, round(avg(2 * thr * got / (got + 2)), 6) AS f1 FROM h GROUP BY 1"))
def alignment_denominators(spark, sf):
    ref = F.array(*map(F.lit, REFERENCE["tables"]))
    rates = [F.avg(a.hit_rate(ref, F.col("tables"), d)).alias(n) for n, d in (("precision", "extracted"), ("recall", "reference"), ("f1", "f1"))]
    return rounded(_scored(spark, sf).groupBy("model_id").agg(*rates), "precision", "recall", "f1")


@query("alignment_per_question", _c(f", own AS (SELECT * FROM (VALUES {facts_by_question()}) o(template, odd, thr2, fhr2, fnr2, ama2)) SELECT model_id, round(avg(thr2), 6) AS thr, round(avg(fhr2), 6) AS fhr, round(avg(fnr2), 6) AS fnr, round(avg(ama2), 6) AS ama FROM candidates c JOIN own o ON o.template = c.template AND o.odd = c.qid % 2 GROUP BY 1"))
def alignment_per_question(spark, sf):
    each = a.scored_by_question(candidates(spark, sf), references(spark, sf), KINDS)
    return rounded(each.groupBy("model_id").agg(*[F.avg(c).alias(c) for c in ("thr", "fhr", "fnr", "ama")]), "thr", "fhr", "fnr", "ama")


@query("argument_types", _c(" SELECT DISTINCT template, 'geometry,geometry' AS types FROM candidates WHERE functions LIKE 'st_within%' AND template NOT IN (5, 8, 9) UNION SELECT DISTINCT template, CASE template WHEN 9 THEN 'unknown,unknown' ELSE 'unknown,geometry' END FROM candidates WHERE template IN (5, 8, 9)"))
def argument_types(spark, sf):
    calls = a.structured(candidates(spark, sf), CATALOG).withColumn("call", a.core_call(F.col("calls"), F.lit("st_within"))).where("call is not null")
    return calls.select("template", F.array_join(a.argument_types(F.col("call.types"), F.col("tables"), KINDS), ",").alias("types")).distinct()


_JSON = "'{\"tables\":[' || CASE tables WHEN '' THEN '' ELSE '\"' || replace(tables, ',', '\",\"') || '\"' END || '],\"functions\":[' || CASE functions WHEN '' THEN '' ELSE '\"' || replace(functions, ',', '\",\"') || '\"' END || ']}'"


@query("structure_json", _c(f" SELECT DISTINCT template, {_JSON} AS structure FROM candidates"))
def structure_json(spark, sf):
    log = _scored(spark, sf).select("template", F.to_json(F.struct(F.array_sort("tables").alias("tables"), "functions")).alias("structure")).distinct()
    back = F.from_json("structure", "tables array<string>, functions array<string>")
    return log.where(F.to_json(back) == F.col("structure"))


@query("argument_misuse", _c(" SELECT model_id, misuse, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY model_id), 6) AS share FROM candidates WHERE fnr = 1 GROUP BY 1, 2"))
def argument_misuse(spark, sf):
    from pyspark.sql import Window

    each = _scored(spark, sf).where("fnr = 1").groupBy("model_id", "misuse").agg(F.count(F.lit(1)).alias("n"))
    return rounded(each.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("model_id"))), "share")


@query("argument_match_case", "SELECT r_regionkey, 0.333333 AS score FROM region")
def argument_match_case(spark, sf):
    ref, got = (F.array(*map(F.lit, x)) for x in (("geometry", "int", "boolean"), ("geometry", "boolean", "int")))
    return rounded(table(spark, sf, "region").select("r_regionkey", a.argument_match(ref, got).alias("score")), "score")


@query("invented_functions", _c(" SELECT 'st_bufer' AS func, count(*) AS n FROM candidates WHERE functions LIKE '%st_bufer%'"))
def invented_functions(spark, sf):
    known = spark.createDataFrame([(n,) for n in ("st_within", "st_area", "st_buffer", "st_point")], "func string")
    return a.invented_functions(_scored(spark, sf), known)


@query("udtf_calls", _c(", one AS (SELECT DISTINCT template, functions FROM candidates WHERE functions <> ''), f AS (SELECT template, unnest(string_split(functions, ',')) AS func FROM one) SELECT template, func, count(*) AS n FROM f GROUP BY 1, 2"))
def udtf_calls(spark, sf):
    from querygrade.functions.registered import register

    register(spark)
    one = candidates(spark, sf).groupBy("template").agg(F.first("sql").alias("sql"))
    one.createOrReplaceTempView("statement_of_template")
    return spark.sql("SELECT template, c.name AS func, count(*) AS n FROM statement_of_template, LATERAL scan_sql_calls(sql) c GROUP BY template, c.name")


@query(
    "value_accuracy",
    """WITH a AS (SELECT o_orderkey, o_custkey % 25 AS model_id, CASE o_orderkey % 4 WHEN 0 THEN o_orderpriority WHEN 1 THEN upper(o_orderpriority) || ' ' WHEN 2 THEN replace(o_orderpriority, '-', ' - ') ELSE o_orderpriority || 'x' END AS got, o_orderpriority AS ref FROM orders),
    v AS (SELECT model_id, o_orderkey // 10 AS stmt, bool_and(lower(regexp_replace(got, '[ \\t\\n\\r\\f\\v]+', '', 'g')) = lower(regexp_replace(ref, '[ \\t\\n\\r\\f\\v]+', '', 'g'))) AS ok FROM a GROUP BY 1, 2)
    SELECT model_id, round(avg(CAST(ok AS INTEGER)), 6) AS accuracy FROM v GROUP BY 1""",
)
def value_accuracy(spark, sf):
    o = table(spark, sf, "orders")
    k = F.col("o_orderkey") % 4
    got = F.when(k == 0, F.col("o_orderpriority")).when(k == 1, F.concat(F.upper("o_orderpriority"), F.lit(" "))).when(k == 2, F.replace("o_orderpriority", F.lit("-"), F.lit(" - "))).otherwise(F.concat("o_orderpriority", F.lit("x")))
    cells = o.select((F.col("o_custkey") % 25).alias("model_id"), F.floor(F.col("o_orderkey") / 10).alias("stmt"), F.lit(0).alias("col"), F.col("o_orderkey").alias("row"), got.alias("got"), F.col("o_orderpriority").alias("ref"))
    reference, answer = cells.select("model_id", "stmt", "col", "row", F.col("ref").alias("value")), cells.select("model_id", "stmt", "col", "row", F.col("got").alias("value"))
    verdict = value_verdict(reference, answer, ["model_id", "stmt"])
    return rounded(m.accuracy(verdict, ["model_id"], "ok"), "accuracy")


@query("norm_text_pairs", "SELECT lang, count(*) AS n, count(DISTINCT md5(lower(regexp_replace(text, '[ \\t\\n\\r\\f\\v]+', '', 'g')))) AS kinds FROM documents GROUP BY 1")
def norm_text_pairs(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.countDistinct(F.md5(norm_value(F.col("text")).cast("binary"))).alias("kinds"))


REFERENCES = {
    "r1": "SELECT count(*) AS n FROM orders WHERE o_orderstatus = 'F'",
    "r2": "SELECT n_name FROM nation WHERE n_regionkey = 1 ORDER BY n_name",
    "r3": "SELECT max(p_size) AS s FROM part",
    "r4": "SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY c_mktsegment",
    "bad1": "SELECT nothing FROM orders",
    "bad2": "DROP TABLE orders",
    "bad3": "SELECT 1 / 0 AS x",
    "bad4": "SELECT FROM WHERE",
}


@query(
    "exec_results",
    "SELECT 'r1' AS qid, 1 AS state, CAST(1 AS BIGINT) AS n_rows, 'number' AS kind UNION ALL SELECT 'r2', 1, (SELECT count(*) FROM nation WHERE n_regionkey = 1), 'text' UNION ALL SELECT 'r3', 1, 1, 'number' UNION ALL SELECT 'r4', 1, (SELECT count(DISTINCT c_mktsegment) FROM customer), 'text' "
    "UNION ALL SELECT 'bad1', 0, NULL, NULL UNION ALL SELECT 'bad2', 0, NULL, NULL UNION ALL SELECT 'bad3', 0, NULL, NULL UNION ALL SELECT 'bad4', 0, NULL, NULL",
)
def exec_results(spark, sf):
    done = execute_candidates(spark, REFERENCES, {n: f"{sf}/{n}.parquet" for n in ("orders", "nation", "part", "customer")})
    return done.select("qid", "state", "n_rows", "kind")


@query("exec_error_classes", "SELECT qid, class, count(*) AS n FROM orders JOIN (VALUES (0, 'bad1', 3), (1, 'bad2', 2), (2, 'bad3', 7), (3, 'bad4', 2)) t(k, qid, class) ON o_orderkey % 4 = k GROUP BY 1, 2")
def exec_error_classes(spark, sf):
    from querygrade.operators.profiles import classify_error

    faulty = {k: v for k, v in REFERENCES.items() if k.startswith("bad")}
    done = execute_candidates(spark, faulty, {"orders": f"{sf}/orders.parquet"})  # each distinct statement once
    attempts = table(spark, sf, "orders").select(F.get(F.array(*map(F.lit, faulty)), (F.col("o_orderkey") % 4).cast("int")).alias("qid"))
    classes = done.select("qid", classify_error(F.col("error"), F.col("sqlstate")).alias("class"))
    return attempts.groupBy("qid").agg(F.count(F.lit(1)).alias("n")).join(classes, "qid").select("qid", "class", "n")


#: References whose whole results are compared; the last is as long as its table.
ANSWERED = {
    "a1": "SELECT count(*) AS n FROM orders WHERE o_orderstatus = 'F'",
    "a2": "SELECT n_name, n_nationkey FROM nation WHERE n_regionkey = 1 ORDER BY n_name",
    "a3": "SELECT max(p_size) AS s FROM part",
    "a4": "SELECT o_orderkey::text AS k FROM orders ORDER BY o_orderkey",
    "a5": "SELECT n_name FROM nation WHERE n_nationkey < 0",
    "a6": "SELECT count(*) AS n FROM nation a JOIN nation b ON a.n_nationkey = b.n_nationkey WHERE concat('POINT(', a.n_nationkey, ' 1)') && 'POLYGON((0 0, 9 0, 9 9, 0 9, 0 0))'",
}
#: (attempt, question, statement): the same in other words, right only if the data say so, wrong, failing.
ATTEMPTS = [
    ("t1", "a1", "SELECT sum(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END) AS n FROM orders"),
    ("t2", "a2", "SELECT upper(n_name) AS name, n_nationkey FROM nation WHERE n_regionkey = 1 ORDER BY 1"),
    ("t3", "a2", "SELECT n_name, n_nationkey FROM nation WHERE n_regionkey = 1 ORDER BY n_name DESC"),
    ("t4", "a2", "SELECT n_name FROM nation WHERE n_regionkey = 1 ORDER BY n_name"),
    ("t5", "a3", "SELECT max(p_size) AS s FROM part WHERE p_partkey % 2 = 0"),
    ("t6", "a4", "SELECT o_orderkey AS k FROM orders ORDER BY 1"),
    ("t7", "a4", "SELECT o_orderkey AS k FROM orders WHERE o_orderkey > 1 ORDER BY 1"),
    ("t8", "a3", "SELECT p_size / 0 FROM part"),
    ("t9", "a6", "SELECT count(*) AS n FROM nation WHERE ST_DWithin(concat('POINT(', n_nationkey, ' 1)'), 'POLYGON((0 0, 9 0, 9 9, 0 9, 0 0))', 0.5)"),
]


def _executed(spark, sf, statements):
    return execute_cells(spark, statements, {n: f"{sf}/{n}.parquet" for n in ("orders", "nation", "part")})


@query(
    "exec_cells",
    "SELECT 'a1' AS qid, 0 AS col, CAST(0 AS BIGINT) AS row, CAST(count(*) AS VARCHAR) AS value FROM orders WHERE o_orderstatus = 'F' UNION ALL SELECT 'a2', 0, row_number() OVER (ORDER BY n_name) - 1, n_name FROM nation WHERE n_regionkey = 1 "
    "UNION ALL SELECT 'a2', 1, row_number() OVER (ORDER BY n_name) - 1, CAST(n_nationkey AS VARCHAR) FROM nation WHERE n_regionkey = 1 UNION ALL SELECT 'a3', 0, 0, CAST(max(p_size) AS VARCHAR) FROM part "
    "UNION ALL SELECT 'a4', 0, row_number() OVER (ORDER BY o_orderkey) - 1, CAST(o_orderkey AS VARCHAR) FROM orders UNION ALL SELECT 'a6', 0, 0, CAST(count(*) AS VARCHAR) FROM nation WHERE n_nationkey <= 9",
)
def exec_cells(spark, sf):
    return freeze_answers(*_executed(spark, sf, ANSWERED))[0].select("qid", "col", "row", "value")


@query("unusable_references", "SELECT 'a5' AS qid, 'gives no row' AS rule WHERE (SELECT count(*) FROM nation WHERE n_nationkey < 0) = 0 UNION ALL SELECT 'bad1', 'does not run' UNION ALL SELECT 'bad4', 'does not run'")
def unusable_references(spark, sf):
    return freeze_answers(*_executed(spark, sf, ANSWERED | {k: REFERENCES[k] for k in ("bad1", "bad4")}))[1]


@query(
    "exec_accuracy",
    "SELECT qid, count(*) AS n, CAST(sum(state) AS BIGINT) AS ran, CAST(sum(ok) AS BIGINT) AS n_correct FROM (SELECT 'a1' AS qid, 1 AS state, CAST(count(*) FILTER (WHERE o_orderstatus = 'F') = sum(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END) AS INTEGER) AS ok FROM orders "
    "UNION ALL SELECT 'a2', 1, 1 UNION ALL SELECT 'a2', 1, CAST(count(*) = 1 AS INTEGER) FROM nation WHERE n_regionkey = 1 UNION ALL SELECT 'a2', 1, 0 "
    "UNION ALL SELECT 'a3', 1, CAST(max(p_size) = max(p_size) FILTER (WHERE p_partkey % 2 = 0) AS INTEGER) FROM part UNION ALL SELECT 'a4', 1, 1 UNION ALL SELECT 'a4', 1, CAST(count(*) FILTER (WHERE o_orderkey <= 1) = 0 AS INTEGER) FROM orders "
    "UNION ALL SELECT 'a3', 0, 0 UNION ALL SELECT 'a6', 1, CAST(count(*) FILTER (WHERE n_nationkey <= 9) = count(*) FILTER (WHERE n_nationkey <= 9.5) AS INTEGER) FROM nation) GROUP BY 1",
)
def exec_accuracy(spark, sf):
    frozen, _ = freeze_answers(*_executed(spark, sf, ANSWERED))
    attempts = spark.createDataFrame([t[:2] for t in ATTEMPTS], "attempt string, qid string")
    each = graded(frozen, attempts, *_executed(spark, sf, {t[0]: t[2] for t in ATTEMPTS}))
    return each.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.sum("state").alias("ran"), F.sum("ok").cast("long").alias("n_correct"))
