"""Structure scan over distinct statements and the alignment measures."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CALL = "struct<name:string,args:array<string>,types:array<string>>"
STRUCTURE = f"syntax_state int, tables array<string>, fields array<string>, functions array<string>, calls array<{CALL}>"


def scan_statements(statements: DataFrame) -> DataFrame:
    """md5 and structure of the distinct texts in ``sql``; parsing happens once for each text.

    The distinct is an aggregation on the digest with map-side combine, so repeated answers cost one parse.
    """
    distinct = statements.groupBy(F.md5(F.col("sql").cast("binary")).alias("md5")).agg(F.first("sql").alias("sql"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from querygrade.functions.sqlscan import scan

        for batch in batches:
            got = [scan(t) for t in batch.column(1).to_pylist()]
            call = pa.struct([("name", pa.string()), ("args", pa.list_(pa.string())), ("types", pa.list_(pa.string()))])
            lists = [pa.array([g[c] for g in got], pa.list_(pa.string())) for c in ("tables", "fields", "functions")]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([g["syntax_state"] for g in got], pa.int32()), *lists, pa.array([g["calls"] for g in got], pa.list_(call))], names=["md5", "sql", "syntax_state", "tables", "fields", "functions", "calls"])

    return distinct.mapInArrow(run, f"md5 string, sql string, {STRUCTURE}")


def resolve_fields(fields: Column, tables: Column, catalog: dict[str, list[str]]) -> Column:
    """Unqualified fields get the one table of the statement that has them, by the catalogue."""

    def one(name: Column) -> Column:
        owners = F.filter(tables, lambda t: F.array_contains(F.array(*[F.lit(f"{a}.{b}") for a, bs in catalog.items() for b in bs]), F.concat(t, F.lit("."), name)))
        return F.when(F.instr(name, ".") > 0, name).when(F.size(owners) == 1, F.concat(F.get(owners, F.lit(0)), F.lit("."), name)).otherwise(name)

    return F.array_distinct(F.transform(fields, one))


def hit_rate(reference: Column, got: Column, denominator: str = "extracted") -> Column:
    """Share of hits among the extracted names (as printed), the reference names, or their F1."""
    hits = F.size(F.array_intersect(reference, got)).cast("double")
    n_got, n_ref = F.size(F.array_distinct(got)), F.size(F.array_distinct(reference))
    if denominator == "f1":
        return F.coalesce(F.try_divide(2 * hits, (n_got + n_ref).cast("double")), F.lit(0.0))
    return F.coalesce(F.try_divide(hits, (n_got if denominator == "extracted" else n_ref).cast("double")), F.lit(0.0))


def core_call(calls: Column, name: Column) -> Column:
    """The first call of the core function in visit order; null if there is none."""
    return F.get(F.filter(calls, lambda c: c["name"] == name), F.lit(0))


def argument_match(reference: Column, got: Column) -> Column:
    """Positions with equal types over the number of reference positions; two empty lists match."""
    same = F.aggregate(F.zip_with(reference, got, lambda a, b: F.coalesce(a == b, F.lit(False)).cast("int")), F.lit(0), lambda a, x: a + x)
    n = F.size(reference)
    return F.when(got.isNull(), 0.0).when(n == 0, (F.size(got) == 0).cast("double")).otherwise(same / n)


def misuse_kind(reference: Column, got: Column) -> Column:
    """none, count, order or type."""
    return F.when(got.isNull() | (reference == got), "none").when(F.size(reference) != F.size(got), "count").when(F.array_sort(reference) == F.array_sort(got), "order").otherwise("type")


def argument_types(types: Column, tables: Column, kinds: dict[str, str]) -> Column:
    """Argument types with columns typed by the catalogue (``table.field`` to type); ambiguous and foreign columns are unknown."""
    catalog: dict[str, list[str]] = {}
    for name in kinds:
        catalog.setdefault(name.split(".")[0], []).append(name.split(".")[1])
    of = F.create_map(*[F.lit(x) for pair in kinds.items() for x in pair])

    def one(t: Column) -> Column:
        name = F.get(resolve_fields(F.array(F.substring(t, 8, 10_000)), tables, catalog), F.lit(0))
        return F.when(~t.startswith("column:"), t).otherwise(F.coalesce(F.try_element_at(of, name), F.lit("unknown")))

    return F.transform(types, one)


def structured(log: DataFrame, catalog: dict[str, list[str]]) -> DataFrame:
    """``log(..., sql)`` with syntax state and structure, fields resolved by the catalogue."""
    structures = scan_statements(log).drop("sql")
    out = log.withColumn("md5", F.md5(F.col("sql").cast("binary"))).join(structures, "md5")
    return out.withColumn("fields", resolve_fields(F.col("fields"), F.col("tables"), catalog))


def _measured(out: DataFrame, core: Column, tables: Column, fields: Column, types: Column, kinds: dict[str, str] | None) -> DataFrame:
    out = out.withColumn("core", core_call(F.col("calls"), core))
    got = F.col("core.types") if kinds is None else argument_types(F.col("core.types"), F.col("tables"), kinds)
    return out.withColumn("got_types", got).withColumns({
        "thr": hit_rate(tables, F.col("tables")), "fhr": hit_rate(fields, F.col("fields")),
        "fnr": F.array_contains("functions", core).cast("int"), "ama": argument_match(types, F.col("got_types")), "misuse": misuse_kind(types, F.col("got_types")),
    })


def scored(log: DataFrame, catalog: dict[str, list[str]], reference: dict) -> DataFrame:
    """``log(..., sql)`` with state, structure and thr, fhr, fnr, ama, misuse of every attempt against one reference."""
    ref = {k: F.array(*map(F.lit, reference[k])) for k in ("tables", "fields", "types")}
    return _measured(structured(log, catalog), F.lit(reference["core"]), ref["tables"], ref["fields"], ref["types"], None)


def scored_by_question(log: DataFrame, references: DataFrame, kinds: dict[str, str]) -> DataFrame:
    """As ``scored``, each attempt against its own question's row of ``references(qid, ref_tables, ref_fields, ref_core, ref_types)``.

    ``kinds`` gives the type of every ``table.field`` of the catalogue, so bare columns are typed arguments.
    """
    catalog: dict[str, list[str]] = {}
    for name in kinds:
        catalog.setdefault(name.split(".")[0], []).append(name.split(".")[1])
    met = structured(log, catalog).join(references, "qid")
    return _measured(met, F.col("ref_core"), F.col("ref_tables"), F.col("ref_fields"), F.col("ref_types"), kinds)


def invented_functions(structures: DataFrame, known: DataFrame) -> DataFrame:
    """func, n: called names that the catalogue ``known(func)`` lacks."""
    called = structures.select(F.explode("functions").alias("func"))
    return called.groupBy("func").agg(F.count(F.lit(1)).alias("n")).join(known, "func", "left_anti")
