"""Theme databases and the questions over their tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from querygrade.functions.units import unit_of
from querygrade.operators.bank import TemplateGenerator, TextGenerator

#: Everyday words that stand for field names in an underspecified question.
SYNONYMS = {"geom": "shape", "name": "title", "id": "number"}


def described(themes: DataFrame, generator: TextGenerator | None = None) -> DataFrame:
    """``themes(db, theme)`` with ``descr``, what the generator writes for the theme; a null theme has none."""
    held = generator or TemplateGenerator()

    @F.pandas_udf(T.StringType())
    def write(prompt: pd.Series) -> pd.Series:
        return pd.Series([None if p is None else held.write(p) for p in prompt], dtype=object)

    return themes.withColumn("descr", write("theme"))


def generate_databases(themes: DataFrame, low: int = 2, high: int = 4, most_values: int = 3) -> DataFrame:
    """Flattened catalogue (db, table, ordinal, field, spark_type, is_geo) of a database for each theme.

    A database has low..high tables by a hash of its key; each table has a key, a name, a geometry and
    1..``most_values`` numbers.
    """
    tables = F.sequence(F.lit(0), F.lit(low - 1) + (unit_of("tables", F.col("db")) % (high - low + 1)).cast("int"))
    of = themes.select("db", F.explode(tables).alias("t"))
    values = F.transform(F.sequence(F.lit(1), 1 + (unit_of("fields", F.col("db"), F.lit("-"), F.col("t")) % most_values).cast("int")), lambda k: F.struct(F.concat(F.lit("v"), k.cast("string")).alias("field"), F.lit("double").alias("spark_type"), F.lit(False).alias("is_geo")))
    fixed = F.array(*[F.struct(F.lit(f).alias("field"), F.lit(kind).alias("spark_type"), F.lit(geo).alias("is_geo")) for f, kind, geo in (("id", "bigint", False), ("name", "string", False), ("geom", "geometry", True))])
    rows = of.select("db", F.concat(F.lit("t"), F.col("db").cast("string"), F.lit("_"), F.col("t").cast("string")).alias("table"), F.posexplode(F.concat(fixed, values)).alias("ordinal", "f"))
    return rows.select("db", "table", "ordinal", "f.*")


def schema_text(catalog: DataFrame) -> DataFrame:
    """db, tables (names in order), schema: all tables of a database with fields and types as text."""
    fields = F.array_sort(F.collect_list(F.struct("ordinal", F.concat_ws(" ", "field", "spark_type").alias("f"))))
    each = catalog.groupBy("db", "table").agg(F.concat(F.col("table"), F.lit("("), F.array_join(fields["f"], ", "), F.lit(")")).alias("text"))
    return each.groupBy("db").agg(F.array_sort(F.collect_list(F.struct("table", "text"))).alias("x")).select("db", F.col("x.table").alias("tables"), F.array_join("x.text", "; ").alias("schema"))


def schema_questions(catalog: DataFrame, bindings: DataFrame, synonyms: dict[str, str] = SYNONYMS) -> DataFrame:
    """A question for each function bound to a database: db, func_id, helper, home, nl_explicit, nl_under, schema.

    ``helper`` is the next bound function of the database (null for its last one), ``home`` the table that a hash names.
    The underspecified text says everyday words for the fields and leaves the table out.  Databases without tables have none.
    """
    after = Window.partitionBy("db").orderBy("func_id")
    asked = bindings.select("db", "func_id", F.lead("func_id").over(after).alias("helper")).join(schema_text(catalog), "db")
    home = F.get("tables", (unit_of("home", F.col("db"), F.lit("-"), F.col("func_id")) % F.size("tables")).cast("int"))
    also = F.when(F.col("helper").isNull(), F.lit("")).otherwise(F.concat(F.lit(" and st_f"), F.col("helper").cast("string")))
    task = F.concat(F.lit("Apply st_f"), F.col("func_id").cast("string"), also, F.lit(" to "))
    fields = ("geom", "name")
    said = [F.lit(synonyms.get(f, f)) for f in fields]
    return asked.withColumn("home", home).select("db", "func_id", "helper", "home", F.concat(task, F.col("home"), F.lit(f".{fields[0]} and give {fields[1]}")).alias("nl_explicit"), F.concat(task, F.lit("the "), said[0], F.lit(" and give the "), said[1]).alias("nl_under"), "schema")
