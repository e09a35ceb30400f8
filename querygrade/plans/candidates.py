"""Candidate statements with structures known by construction.

Each attempt gets one of the templates below by a hash of its key; what a right scan finds in a template is written
beside it, so the scan is checked against facts that no parser made.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from querygrade.functions.units import sql_unit as u
from querygrade.functions.units import unit_of
from querygrade.plans.fixtures import attempts

CATALOG = {"sites": ["id", "geom"], "zones": ["name", "geom"]}
REFERENCE = {"tables": ["sites", "zones"], "fields": ["sites.geom", "sites.id", "zones.geom", "zones.name"], "core": "st_buffer", "types": ["geometry", "integer", "text"]}
_ALL = REFERENCE["fields"]
_TYPES = REFERENCE["types"]


@dataclass
class Template:
    sql: str
    state: int = 1
    tables: list[str] = field(default_factory=lambda: ["sites", "zones"])
    fields: list[str] = field(default_factory=lambda: list(_ALL))
    functions: list[str] = field(default_factory=lambda: ["st_within", "st_area", "st_buffer", "st_point"])
    types: list[str] | None = field(default_factory=lambda: list(_TYPES))  # of the core call; None: no such call


_JOIN = "SELECT s.id FROM sites s JOIN zones z ON ST_Within(s.geom, z.geom) WHERE z.name = '{name}' AND "
TEMPLATES = [
    Template(_JOIN + "ST_Area(ST_Buffer(ST_Point(1, 2), {size}, 'quad_segs=8')) > 1"),
    Template(_JOIN + "ST_Area(ST_Buffer({size}, ST_Point(1, 2), 'quad_segs=8')) > 1", types=["integer", "geometry", "text"]),
    Template(_JOIN + "ST_Area(ST_Buffer(ST_Point(1, 2), {size})) > 1", types=["geometry", "integer"]),
    Template(_JOIN + "ST_Area(ST_Bufer(ST_Point(1, 2), {size}, 'quad_segs=8')) > 1", functions=["st_within", "st_area", "st_bufer", "st_point"], types=None),
    Template(_JOIN.replace("s.id", "s.idd") + "ST_Area(ST_Buffer(ST_Point(1, 2), {size}, 'quad_segs=8')) > 1", fields=["sites.geom", "sites.idd", "zones.geom", "zones.name"]),
    Template(_JOIN.replace("sites s", "site s") + "ST_Area(ST_Buffer(ST_Point(1, 2), {size}, 'quad_segs=8')) > 1", tables=["site", "zones"], fields=["site.geom", "site.id", "zones.geom", "zones.name"]),
    Template(_JOIN + "ST_Area(ST_Buffer(ST_Point(1, 2), {size}, 'quad_segs=8') > 1", 0, [], [], [], None),
    Template("SELECT s.id FROM sites s WHERE", 0, [], [], [], None),
    Template("WITH c AS (SELECT geom, id FROM sites) SELECT c.id FROM c WHERE ST_Within(c.geom, ST_Buffer(ST_Point(1, 2), {size}, 'quad_segs=8'))", 1, ["sites"], ["c.geom", "c.id", "sites.geom", "sites.id"], ["st_within", "st_buffer", "st_point"]),
    Template("SELECT id FROM sites WHERE ST_Within(geom, (SELECT geom FROM zones WHERE name = '{name}'))", 1, ["sites", "zones"], ["geom", "sites.id", "zones.name"], ["st_within"], None),
    Template("SELECT s.id FROM public.sites s, zones z WHERE s.geom && z.geom AND z.name::text = '{name}' AND ST_Buffer(ST_Point(1, 2), {size}::integer, 'quad_segs=8') IS NOT NULL", functions=["st_buffer", "st_point"]),
    Template("DELETE FROM sites WHERE id = {size}", 1, ["sites"], ["sites.id"], [], None),
    Template("", 0, [], [], [], None),
    Template("SELECT x.id FROM sites x WHERE EXISTS (SELECT 1 FROM zones x WHERE x.name = '{name}')", 1, ["sites", "zones"], ["sites.id", "zones.name"], [], None),
    Template("WITH sites AS (SELECT id FROM sites) SELECT s.id FROM sites s WHERE s.id = {size}", 1, ["sites"], ["sites.id"], [], None),
    Template("DELETE FRM sites WHERE id = {size}", 0, [], [], [], None),
    Template("INSERT INTO zones (name, geom) SELECT s.id, ST_Buffer(s.geom::geometry, {size}, 'x') FROM sites s", 1, ["sites", "zones"], ["sites.geom", "sites.id", "zones.geom", "zones.name"], ["st_buffer"]),
    Template('SELECT "s".id /* key */ FROM sites AS "s" -- all\nORDER BY ST_Buffer(s.geom::geometry, {size}, \'x\') <-> ST_Point(1, 2) LIMIT 3', 1, ["sites"], ["sites.geom", "sites.id"], ["st_buffer", "st_point"]),
    Template("SELECT s.id FROM sites s UNION ALL SELECT z.name FROM zones z WHERE ST_Area(z.geom) > {size}", 1, ["sites", "zones"], ["sites.id", "zones.geom", "zones.name"], ["st_area"], None),
    Template(_JOIN.replace("zones z ON", "zones z ON o.k = z.k AND").replace("FROM sites s", "FROM sites s CROSS JOIN owners o") + "ST_Buffer(ST_Point(1, 2), {size}, true) IS NOT NULL", tables=["owners", "sites", "zones"], fields=["owners.k", *_ALL, "zones.k"], functions=["st_within", "st_buffer", "st_point"], types=["geometry", "integer", "boolean"]),
]


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """model_id, qid, variant, run, family, template, sql of the SQL families."""
    log = attempts(spark, sf_dir).where("family <> 'concept'")
    key = F.concat_ws("-", "model_id", "qid", "variant", "run")
    which = (unit_of("c", key) % len(TEMPLATES)).cast("int")
    text = F.element_at(F.array(*[F.lit(t.sql) for t in TEMPLATES]), F.col("template") + 1)
    filled = F.replace(F.replace(text, F.lit("{name}"), F.replace(F.col("name"), F.lit("'"), F.lit("''"))), F.lit("{size}"), F.col("size").cast("string"))
    return log.select("model_id", "qid", "variant", "run", "family", "name", "size", which.alias("template")).withColumn("sql", filled).drop("name", "size")


def _joined(values: list[str]) -> str:
    return ",".join(sorted(values))


def facts() -> list[tuple]:
    """template, state, tables, fields, functions, thr, fhr, fnr, ama and the kind of misuse, from the lists above."""
    out = []
    for k, t in enumerate(TEMPLATES):
        hit = lambda got, ref: len(set(got) & set(ref)) / len(got) if got else 0.0
        ama = sum(a == b for a, b in zip(t.types or [], _TYPES, strict=False)) / len(_TYPES)
        misuse = "none" if t.types is None or t.types == _TYPES else "count" if len(t.types) != len(_TYPES) else "order" if sorted(t.types) == sorted(_TYPES) else "type"
        out.append((k, t.state, _joined(t.tables), _joined(t.fields), ",".join(t.functions), hit(t.tables, REFERENCE["tables"]), hit(t.fields, _ALL), int(t.types is not None), ama, misuse))
    return out


KINDS = {"sites.id": "integer", "sites.geom": "geometry", "zones.name": "text", "zones.geom": "geometry"}
#: References by question: even ones ask for a buffer over both tables, odd ones for containment of sites.
BY_QUESTION = [REFERENCE, {"tables": ["sites"], "fields": ["sites.geom"], "core": "st_within", "types": ["geometry", "geometry"]}]
#: Types of the containment call where they are not two geometries: foreign tables, common tables, ambiguous names and subqueries are unknown.
WITHIN = {5: ["unknown", "geometry"], 8: ["unknown", "geometry"], 9: ["unknown", "unknown"]}


def references(spark: SparkSession, sf_dir: str) -> DataFrame:
    """qid, ref_tables, ref_fields, ref_core, ref_types of every question."""
    from querygrade.sources.tables import table

    odd = F.col("p_partkey") % 2 == 1
    arrays = {k: F.when(odd, F.array(*map(F.lit, BY_QUESTION[1][k]))).otherwise(F.array(*map(F.lit, BY_QUESTION[0][k]))) for k in ("tables", "fields", "types")}
    core = F.when(odd, BY_QUESTION[1]["core"]).otherwise(BY_QUESTION[0]["core"])
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("qid"), *[c.alias(f"ref_{k}") for k, c in arrays.items()], core.alias("ref_core"))


def facts_by_question() -> str:
    """SQL rows (template, odd, thr, fhr, fnr, ama) from the lists above."""
    rows = []
    for k, t in enumerate(TEMPLATES):
        for odd, ref in enumerate(BY_QUESTION):
            hit = lambda got, want: len(set(got) & set(want)) / len(got) if got else 0.0
            got = t.types if not odd else WITHIN.get(k, ["geometry", "geometry"]) if "st_within" in t.functions else None
            ama = sum(a == b for a, b in zip(got or [], ref["types"], strict=False)) / len(ref["types"])
            rows.append((k, odd, hit(t.tables, ref["tables"]), hit(t.fields, ref["fields"]), int(ref["core"] in t.functions), ama))
    return ", ".join(map(repr, rows))


def _sql_rows() -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else repr(x) for x in row) + ")" for row in facts())


CTES = f"""facts AS (SELECT * FROM (VALUES {_sql_rows()}) f(template, state, tables, fields, functions, thr, fhr, fnr, ama, misuse)),
candidates AS (SELECT a.model_id, a.qid, a.family, f.* FROM attempts a JOIN facts f ON f.template = {u("'c' || model_id || '-' || qid || '-' || variant || '-' || run")} % {len(TEMPLATES)} WHERE a.family <> 'concept')"""
