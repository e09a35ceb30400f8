"""Guarded execution of candidate statements: queries only, own session, timeout, error capture, result cells."""

from __future__ import annotations

import re
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from querygrade.functions.dialect import to_spark_sql
from querygrade.functions.geometry_udfs import register
from querygrade.functions.sqlscan import STATEMENTS, SyntaxFault, parse
from querygrade.operators.values import value_verdict
from querygrade.sources.tables import shared_folder

#: Text that a geometry's WKT or EWKT begins with.
WKT = r"(?i)^\s*(SRID=\d+;)?\s*(MULTI)?(POINT|LINESTRING|POLYGON)\s*Z?M?\s*(\(|EMPTY)"
REFUSED = re.compile(r"\b(reflect|java_method|try_reflect|read_files|text|parquet|csv|json|orc|binaryfile)\s*[.(]\s*['`/]", re.I)


def result_kind(schema: T.StructType) -> str:
    """geometry, number, boolean or text, by the first column."""
    if not schema.fields:
        return "text"
    kind = schema.fields[0].dataType
    if isinstance(kind, T.BooleanType):
        return "boolean"
    if isinstance(kind, T.NumericType):
        return "number"
    return "geometry" if isinstance(kind, T.BinaryType) else "text"


def guard(text: str) -> None:
    """Refuse everything but one query over the given views."""
    first = (text.strip().split(None, 1) or [""])[0].lower()
    if first in STATEMENTS:
        raise SyntaxFault(f"syntax error: statement kind {first} is refused")
    if REFUSED.search(text):
        raise SyntaxFault("syntax error: files and reflection are refused")
    parse(text)


def _cause(fault: Exception) -> tuple[str | None, str]:
    """SQLSTATE and text of the deepest cause that has a state (a failed write wraps what the statement raised)."""
    state, text, at = None, str(fault), fault
    while at is not None:
        found = at.getSqlState() if hasattr(at, "getSqlState") else None
        if found:
            state, text = found, str(at)
        at = getattr(at, "_cause", None)
    return state, text[:500]


def _cells_of(answer: DataFrame) -> DataFrame:
    """at, cells: every row as text values in column order; ``at`` rises in result order, its high bits are the partition."""
    names = [f"c{k}" for k in range(len(answer.columns))]  # result columns may share a name
    text = [F.base64(n) if isinstance(f.dataType, T.BinaryType) else F.col(n).cast("string") if isinstance(f.dataType, T.AtomicType) else F.to_json(F.struct(n)) for n, f in zip(names, answer.schema.fields, strict=True)]
    return answer.toDF(*names).select(F.monotonically_increasing_id().alias("at"), F.array(*text).cast("array<string>").alias("cells"))


def execute_cells(spark: SparkSession, statements: dict[str, str], sources: dict[str, str], timeout_s: int = 120, pool: int = 4, bridge: bool = True) -> tuple[DataFrame, DataFrame]:
    """(results, cells) of distinct statements.

    results: one row for each statement with state, number of rows, kind of its first column, SQLSTATE and error text.
    cells: qid, col, row, value of every result row, in result order from 0.  Executors write the rows and count
    them, without a cap; nothing but one row a statement comes to the driver.  ``bridge`` translates spatial
    operators first and offers the spatial functions.  Statements are few (one for each text after deduplication);
    each is its own job in a bounded pool of sessions whose views are read-only Parquet tables.
    """
    base = f"{shared_folder(spark)}/result-cells-{uuid.uuid4().hex}"
    order = list(statements)
    sessions = {qid: spark.newSession() for qid in order}

    def one(k: int) -> tuple:
        qid, session = order[k], sessions[order[k]]
        try:
            guard(statements[qid])
            for name, path in sources.items():
                session.read.parquet(path).createOrReplaceTempView(name)
            if bridge:
                register(session)
            session.addTag(f"candidate-{k}")
            answer = session.sql(to_spark_sql(statements[qid]) if bridge else statements[qid])
            _cells_of(answer).write.parquet(f"{base}/k={k}")
            return qid, k, 1, result_kind(answer.schema), None, None
        except SyntaxFault as e:
            return qid, k, 0, None, "42601", str(e)[:500]
        except Exception as e:  # analysis and run-time errors of untrusted text are results here
            return qid, k, 0, None, *_cause(e)

    with ThreadPoolExecutor(pool) as workers:
        futures = [workers.submit(one, k) for k in range(len(order))]
        rows = []
        for k, f in enumerate(futures):
            try:
                rows.append(f.result(timeout=timeout_s))
            except TimeoutError:
                sessions[order[k]].interruptTag(f"candidate-{k}")
                rows.append((order[k], k, 0, None, "57014", "timeout"))
    done = spark.createDataFrame(rows, "qid string, k int, state int, kind string, sqlstate string, error string")
    good = [f"{base}/k={r[1]}" for r in rows if r[2]]
    shape = "at long, cells array<string>, k int"
    kept = spark.read.schema(shape).option("basePath", base).parquet(*good) if good else spark.createDataFrame([], shape)
    part = F.shiftright("at", 33)
    sizes = kept.groupBy("k", part.alias("part")).agg(F.count(F.lit(1)).alias("n"))  # one row for each statement and task
    before = sizes.select("k", "part", (F.sum("n").over(Window.partitionBy("k").orderBy("part")) - F.col("n")).alias("before"))
    totals = sizes.groupBy("k").agg(F.sum("n").alias("n_rows"))
    text_shape = kept.where(F.get("cells", F.lit(0)).rlike(WKT)).select("k").distinct().withColumn("shape", F.lit(True))
    kind = F.when((F.col("kind") == "text") & F.col("shape"), "geometry").otherwise(F.col("kind"))
    n = F.when(F.col("state") == 1, F.coalesce("n_rows", F.lit(0)))
    results = done.join(totals, "k", "left").join(text_shape, "k", "left").select("qid", "state", n.alias("n_rows"), kind.alias("kind"), "sqlstate", "error")
    placed = kept.withColumn("part", part).join(before, ["k", "part"]).join(done.select("k", "qid"), "k")
    cells = placed.select("qid", (F.col("before") + F.col("at").bitwiseAND((1 << 33) - 1)).alias("row"), F.posexplode("cells").alias("col", "value"))
    return results, cells.select("qid", "col", "row", "value")


def execute_candidates(spark: SparkSession, statements: dict[str, str], sources: dict[str, str], timeout_s: int = 120, pool: int = 4) -> DataFrame:
    """The results of :func:`execute_cells` alone."""
    return execute_cells(spark, statements, sources, timeout_s, pool)[0]


def freeze_answers(results: DataFrame, cells: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cells of the references that ran and gave rows, qid and rule of those that did not)."""
    rule = F.when(F.col("state") == 0, "does not run").when(F.col("n_rows") == 0, "gives no row")
    return cells.join(results.where("state = 1 AND n_rows > 0").select("qid"), "qid", "left_semi"), results.select("qid", rule.alias("rule")).where("rule IS NOT NULL")


def graded(frozen: DataFrame, attempts: DataFrame, results: DataFrame, cells: DataFrame, num_tol: float | None = None) -> DataFrame:
    """attempt, qid, state, ok of ``attempts(attempt, qid, ...)``: did it run, and do its cells agree with the frozen ones.

    ``results`` and ``cells`` hold the attempts' own executions, with the attempt as ``qid``.
    """
    asked = attempts.select("attempt", "qid").join(results.select(F.col("qid").alias("attempt"), "state"), "attempt")
    wanted = asked.where("state = 1").join(frozen, "qid").select("attempt", "col", "row", "value")
    given = cells.withColumnRenamed("qid", "attempt")
    verdict = value_verdict(wanted, given, ["attempt"], num_tol=num_tol)
    return asked.join(verdict, "attempt", "left").select("attempt", "qid", "state", F.coalesce("ok", F.lit(0)).alias("ok"))
