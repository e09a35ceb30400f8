"""Question bank: catalogue, generated questions, weakened prompts, bindings, validators and review."""

from __future__ import annotations

from typing import Protocol

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from querygrade.functions.units import unit_of

#: Questions of each concept subtask that a function gets.
PER_FUNCTION = {"purpose": 2, "parameter": 2, "return_type": 1, "rule": 2}
#: Colloquial replacements of an underspecified prompt, in order (pattern, replacement).
WEAKER = [(r" with SRID [0-9]+", ""), (r"\bMULTIPOLYGON\b", "shape"), (r"\bPOLYGON\b", "shape"), (r"\bLINESTRING\b", "line"), (r"\bgeometry of type ", ""), (r"\bcalculate the buffer\b", "widen")]


class TextGenerator(Protocol):
    """A language model or a stand-in for it."""

    def write(self, prompt: str) -> str: ...


class TemplateGenerator:
    """Deterministic stand-in: the prompt's facts in a fixed frame."""

    def write(self, prompt: str) -> str:
        return f"Database about {prompt.strip().lower()}"


def function_docs(part: DataFrame) -> DataFrame:
    """func_id, func_name, sig, ret, std, examples: one row for each function."""
    ranked = part.withColumn("func_id", F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int"))
    examples = F.sort_array(F.collect_list(F.struct(F.col("p_partkey").alias("j"), F.concat(F.lit("SELECT ST_F"), F.col("func_id").cast("string"), F.lit("("), F.col("p_size").cast("string"), F.lit(")")).alias("query"), F.col("p_retailprice").cast("string").alias("result"))))
    kinds = F.element_at(F.array(*map(F.lit, ("geometry", "numeric", "text", "boolean"))), F.col("func_id") % 4 + 1)
    return ranked.groupBy("func_id").agg(examples.alias("examples")).withColumns({"func_name": F.concat(F.lit("st_f"), F.col("func_id").cast("string")), "sig": F.array(F.lit("geometry"), F.lit("integer"), F.lit("text")), "ret": kinds, "descr": F.concat(F.lit("Function number "), F.col("func_id").cast("string"))})


def function_examples(docs: DataFrame) -> DataFrame:
    return docs.select("func_id", F.posexplode("examples").alias("j", "e")).select("func_id", "j", "e.query", "e.result")


def spark_function_docs(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """func, n_docs: the session's own functions (a real catalogue; a driver-sized list) and how many texts of ``docs`` name each as a word."""
    names = spark.createDataFrame([(r[0],) for r in spark.sql("SHOW SYSTEM FUNCTIONS").collect()], "func string")
    words = docs.select(F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z0-9_]+"))).alias("func"))
    counts = words.join(F.broadcast(names), "func", "left_semi").groupBy("func").agg(F.count(F.lit(1)).alias("n_docs"))
    return names.join(counts, "func", "left").select("func", F.coalesce("n_docs", F.lit(0).cast("long")).alias("n_docs"))


def concept_questions(docs: DataFrame, per_function: dict[str, int] = PER_FUNCTION) -> DataFrame:
    """qid, func_id, subtask, k, truth: choice keys A-D, or True/False by a hash."""
    plan = F.array(*[F.struct(F.lit(s).alias("subtask"), F.lit(k).alias("k")) for s, n in per_function.items() for k in range(n)])
    rows = docs.select("func_id", "func_name", "ret", "sig", F.inline(plan))
    choice = F.col("subtask").isin("purpose", "return_type")
    drawn = unit_of("truth", F.col("func_id"), F.col("subtask"), F.col("k"))
    truth = F.when(choice, F.chr(65 + drawn % 4)).otherwise(F.when(drawn % 2 == 0, "True").otherwise("False"))
    return rows.withColumn("truth", truth).withColumn("qid", F.concat_ws("-", F.col("func_id").cast("string"), "subtask", F.col("k").cast("string")))


def add_distractors(questions: DataFrame, docs: DataFrame, k: int = 3) -> DataFrame:
    """options of choice questions: the right name at the key's place among the k nearest other names."""
    names = docs.select(F.col("func_id").alias("other_id"), F.col("func_name").alias("other"))
    near = docs.select("func_id", "func_name").join(F.broadcast(names), F.col("func_id") != F.col("other_id"))  # the catalogue: hundreds of rows
    w = Window.partitionBy("func_id").orderBy(F.levenshtein("func_name", "other"), "other")
    wrong = near.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).groupBy("func_id").agg(F.sort_array(F.collect_list(F.struct("r", "other"))).alias("w"))
    at = F.ascii("truth") - 65
    placed = F.transform(F.sequence(F.lit(0), F.lit(k)), lambda i: F.when(i == at, F.col("func_name")).otherwise(F.get(F.col("w.other"), F.when(i < at, i).otherwise(i - 1))))
    return questions.where(F.col("truth").isin(*"ABCD")).join(wrong, "func_id").withColumn("options", placed).drop("w")


def perturb_signature(sig: Column, kind: str) -> Column:
    """A false parameter statement: order, type or count."""
    if kind == "order":
        return F.concat(F.slice(sig, 2, 1), F.slice(sig, 1, 1), F.slice(sig, F.lit(3), F.size(sig)))
    if kind == "type":
        return F.transform(sig, lambda t, i: F.when(i == 0, F.when(t == "text", "integer").otherwise("text")).otherwise(t))
    return F.slice(sig, F.lit(1), F.size(sig) - 1)


def syntax_prompt(example: Column, ret: Column) -> Column:
    return F.concat(F.lit("Write a statement like "), example, F.lit(" that returns a "), ret, F.lit(" geometry of type POLYGON with SRID 4326"))


def underspecify(text: Column, rules: list[tuple[str, str]] = WEAKER) -> Column:
    for pattern, put in rules:
        text = F.regexp_replace(text, pattern, put)
    return text


def bind_functions(docs: DataFrame, databases: DataFrame, low: int = 4, high: int = 8) -> DataFrame:
    """db, func_id: low..high functions for each database in hash order, every function at least once.

    The repair gives each uncovered function to the database of its hash, so coverage needs no search.
    """
    n = F.lit(low) + unit_of("size", F.col("db")) % (high - low)
    pairs = databases.withColumn("n", n).crossJoin(docs.select("func_id"))
    w = Window.partitionBy("db").orderBy(unit_of("bind", F.col("db"), F.lit("-"), F.col("func_id")), "func_id")
    drawn = pairs.withColumn("r", F.row_number().over(w)).where(F.col("r") <= F.col("n")).select("db", "func_id")
    missing = docs.select("func_id").join(drawn.select("func_id").distinct(), "func_id", "left_anti")
    place = Window.partitionBy("func_id").orderBy(unit_of("repair", F.col("db"), F.lit("-"), F.col("func_id")), "db")
    repaired = missing.crossJoin(databases.select("db")).withColumn("r", F.row_number().over(place)).where("r = 1").select("db", "func_id")
    return drawn.unionByName(repaired)


def annotate_questions(examples: DataFrame) -> DataFrame:
    """``examples(..., sql)`` with the first function of each statement and its argument types, by the structure scan."""
    from querygrade.operators.alignment import scan_statements

    first = scan_statements(examples).select("md5", F.get("calls", F.lit(0)).alias("call"))
    met = examples.withColumn("md5", F.md5(F.col("sql").cast("binary"))).join(first, "md5", "left")
    return met.select(*examples.columns, F.col("call.name").alias("func"), F.col("call.types").alias("types"))


def seed_examples(bank: DataFrame, n: int) -> DataFrame:
    """n questions of each family in hash order, as seeds for generated ones."""
    w = Window.partitionBy("family").orderBy(unit_of("seed", F.col("qid")), "qid")
    return bank.withColumn("r", F.row_number().over(w)).where(F.col("r") <= n).drop("r")


def distinct_questions(bank: DataFrame) -> DataFrame:
    """qid, n: the least question of each family and normalised text (letters and digits, lower case), and how many share it."""
    return bank.groupBy("family", F.regexp_replace(F.lower("name"), "[^a-z0-9]", "").alias("key")).agg(F.min("qid").alias("qid"), F.count(F.lit(1)).alias("n")).select("qid", "n")


def validate_choices(options: DataFrame) -> DataFrame:
    """qid, rule of every violation: distinct options, exactly one of them right, at its key."""
    rules = {
        "options differ": F.size(F.array_distinct("options")) == F.size("options"),
        "one right option": F.size(F.filter("options", lambda o: o == F.col("func_name"))) == 1,
        "key points to it": F.get("options", F.ascii("truth") - 65) == F.col("func_name"),
    }
    checks = F.array(*[F.struct(F.lit(n).alias("rule"), F.coalesce(ok, F.lit(False)).alias("ok")) for n, ok in rules.items()])
    return options.select("qid", F.inline(checks)).where(~F.col("ok")).select("qid", "rule")


CATALOG_RULES = {
    "field names are plain": "field NOT RLIKE '^[a-z_][a-z0-9_]*$'",
    "types are known": "spark_type NOT IN ('int', 'bigint', 'double', 'string', 'timestamp', 'timestamp_ntz', 'array<float>', 'geometry')",
}


def validate_catalog(catalog: DataFrame) -> DataFrame:
    """rule, n: violations of a flattened catalogue (db, table, ordinal, field, spark_type, is_geo)."""
    out = [catalog.where(cond).agg(F.lit(rule).alias("rule"), F.count(F.lit(1)).alias("n")) for rule, cond in CATALOG_RULES.items()]
    per_db = catalog.groupBy("db").agg(F.count_if("is_geo").alias("geo"), F.countDistinct("table").alias("tables"))
    out.append(per_db.where("geo = 0").agg(F.lit("a geometry field in each database").alias("rule"), F.count(F.lit(1)).alias("n")))
    out.append(catalog.groupBy("db", "table", "field").count().where("count > 1").agg(F.lit("fields differ").alias("rule"), F.count(F.lit(1)).alias("n")))
    total = out[0]
    for o in out[1:]:
        total = total.unionByName(o)
    return total


def catalog_summary(catalog: DataFrame) -> DataFrame:
    return catalog.groupBy("db").agg(F.countDistinct("table").alias("n_tables"), F.count(F.lit(1)).alias("n_fields"), F.count_if("is_geo").alias("n_geo"))


def bank_summary(bank: DataFrame) -> DataFrame:
    """Counts by family, subtask and variant with all subtotals."""
    return bank.rollup("family", "subtask", "variant").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level"))


def adjudicate(reviews: DataFrame) -> DataFrame:
    """verdict of ``reviews(key, a, b, c)``: what two reviewers agree on, else the third's."""
    return reviews.withColumn("verdict", F.when(F.col("a") == F.col("b"), F.col("a")).otherwise(F.col("c")))


def kappa(reviews: DataFrame) -> DataFrame:
    """Cohen's agreement of two reviewers with verdicts 0/1."""
    m = reviews.agg(F.avg((F.col("a") == F.col("b")).cast("double")).alias("po"), F.avg(F.col("a").cast("double")).alias("pa"), F.avg(F.col("b").cast("double")).alias("pb"))
    pe = F.col("pa") * F.col("pb") + (1 - F.col("pa")) * (1 - F.col("pb"))
    return m.select(((F.col("po") - pe) / (1 - pe)).alias("kappa"))


def render_prompt(family: str, question: Column, schema: Column | None = None) -> Column:
    """Prompt text with strict output rules."""
    rule = {"concept": "Answer with the option only.", "syntax": "Answer with one SQL statement only.", "schema": "Answer with one SQL statement over the given tables only."}[family]
    parts = [question] + ([F.concat(F.lit("Tables: "), schema)] if schema is not None else []) + [F.lit(rule)]
    return F.concat_ws("\n", *parts)


def retrieve_functions(questions: DataFrame, docs: DataFrame, k: int = 3) -> DataFrame:
    """qid, rank, func_id: the k catalogue entries that share most words with a question (token equi-join)."""
    asked = questions.select("qid", F.explode(F.array_distinct(F.split(F.lower("text"), r"[^a-z0-9]+"))).alias("token")).where("token <> ''")
    words = docs.select("func_id", F.explode(F.array_distinct(F.split(F.lower("text"), r"[^a-z0-9]+"))).alias("token")).where("token <> ''")
    shared = asked.join(words, "token").groupBy("qid", "func_id").agg(F.count(F.lit(1)).alias("hits"))
    w = Window.partitionBy("qid").orderBy(F.desc("hits"), "func_id")
    return shared.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "func_id")


#: Rules of the prompt-based contestant, in order: pattern of the prompt, statement frame (``%s``: the name asked for).
PROMPT_RULES = [(r"\bboolean\b", "SELECT ST_Intersects(a.geom, b.geom) FROM sites a JOIN zones b ON true -- %s"), (r"\bnumber\b", "SELECT ST_Area(geom) FROM zones -- %s"), (r"\btext\b", "SELECT ST_AsText(geom) FROM sites -- %s"), (r"", "SELECT geom FROM sites -- %s")]


def prompt_rule_strategy(asked: DataFrame, rules: list[tuple[str, str]] = PROMPT_RULES) -> DataFrame:
    """qid, rule, sql for ``asked(qid, prompt, name)``: the first rule whose pattern the prompt holds fills its frame.

    No matching rule or a null prompt gives null ``rule`` and ``sql``, a missing answer."""
    rule, sql = F.lit(None).cast("int"), F.lit(None).cast("string")
    for k in range(len(rules) - 1, -1, -1):
        pattern, frame = rules[k]
        hit = F.col("prompt").rlike(pattern)
        rule = F.when(hit, F.lit(k)).otherwise(rule)
        sql = F.when(hit, F.format_string(frame, F.coalesce("name", F.lit("")))).otherwise(sql)
    return asked.select("qid", rule.alias("rule"), sql.alias("sql"))


def insertion_rows(offered: DataFrame, samples: DataFrame) -> DataFrame:
    """Distinct offered rows that differ from every sample row; nulls are equal, columns are those of ``offered``."""
    cols = offered.columns
    shown = samples.select(*cols).distinct().alias("s")
    same = [F.col(f"o.`{c}`").eqNullSafe(F.col(f"s.`{c}`")) for c in cols]
    on = same[0]
    for more in same[1:]:
        on = on & more
    return offered.distinct().alias("o").join(shown, on, "left_anti")
