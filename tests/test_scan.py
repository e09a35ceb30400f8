import pytest

from querygrade.functions.sqlscan import scan
from querygrade.plans.candidates import TEMPLATES


@pytest.mark.parametrize("template", TEMPLATES)
def test_templates_scan_as_built(template):
    got = scan(template.sql.replace("{size}", "7").replace("{name}", "x"))
    assert got["syntax_state"] == template.state and sorted(got["tables"]) == sorted(template.tables) and got["functions"] == template.functions


@pytest.mark.parametrize("text,state", [
    ("select 1", 1), ("select a from t where", 0), ("select (a from t", 0), ("selec a", 0), ("select a b c from t", 0), ("select * from a natural join b", 1), ("select * from a join b", 0),
    ("select count(*) filter (where q > 1) over (partition by k order by j rows between 1 preceding and current row) from t", 1), ("select $$it's$$, e'a''b', \"q\"\"x\" from t", 1),
    ("values (1, 2), (3, 4)", 1), ("with recursive r(n) as (select 1 union all select n + 1 from r) select * from r", 1), ("select case when a then 1", 0), ("drop table x", 1), ("", 0), (None, 0),
    ("select a from t order by b desc nulls last limit 5 offset 2", 1), ("select array[1, 2][1], row(1, 2), x::numeric(10, 2)[] from t", 1), ("select 'open", 0),
])
def test_states(text, state):
    assert scan(text)["syntax_state"] == state


def test_deep_nesting_and_long_texts_end():
    assert scan("select " + "(" * 5000 + "1" + ")" * 5000)["syntax_state"] == 0
    assert scan("select " + "+".join(["1"] * 20000))["syntax_state"] == 1
    assert scan("select 1 " + " " * 300_000)["syntax_state"] == 1


def test_names_resolve_through_aliases_and_ctes():
    got = scan("WITH c AS (SELECT z.g FROM public.zones AS z) SELECT c.g, s.id FROM c JOIN sites s ON s.id = 1")
    assert got["tables"] == ["zones", "sites"] and set(got["fields"]) == {"zones.g", "c.g", "sites.id"}


@pytest.mark.parametrize("text,tables,fields", [
    ("SELECT x.a FROM t1 x WHERE EXISTS (SELECT 1 FROM t2 x WHERE x.b = 1)", {"t1", "t2"}, {"t1.a", "t2.b"}),
    ("SELECT q.c FROM (WITH sites AS (SELECT 1 AS c) SELECT c FROM sites) q JOIN sites s ON s.d = q.c", {"sites"}, {"q.c", "c", "sites.d"}),
    ("SELECT x.a FROM t1 x UNION ALL SELECT x.a FROM t2 x", {"t1", "t2"}, {"t1.a", "t2.a"}),
    ("WITH RECURSIVE r AS (SELECT 1 AS n UNION ALL SELECT n FROM r) SELECT r.n FROM r", set(), {"n", "r.n"}),
    ("SELECT s.id FROM sites s ORDER BY s.k", {"sites"}, {"sites.id", "sites.k"}),
    ("UPDATE t1 AS u SET a = u.b + 1 FROM t2 WHERE t2.k = u.k RETURNING u.a", {"t1", "t2"}, {"a", "t1.b", "t2.k", "t1.k", "t1.a"}),
    ("INSERT INTO t SELECT ST_Area(g) FROM u", {"t", "u"}, {"g"}),
])
def test_names_hold_in_their_scope(text, tables, fields):
    got = scan(text)
    assert got["syntax_state"] == 1 and set(got["tables"]) == tables and set(got["fields"]) == fields


@pytest.mark.parametrize("text", ["DELETE FRM sites", "INSERT INTO t", "UPDATE t SET", "UPDATE t a = 1", "DELETE FROM t WHERE", "INSERT INTO t (a, b) VALUES (1, 2", "DELETE FROM t x y"])
def test_faulty_statements_of_other_kinds(text):
    assert scan(text)["syntax_state"] == 0


def test_spatial_operators_become_functions():
    from querygrade.functions.dialect import to_spark_sql

    cases = {
        "SELECT a.id FROM a JOIN b ON a.geom && b.geom": "SELECT a.id FROM a JOIN b ON ST_BBoxOverlaps(a.geom, b.geom)",
        "SELECT (g <-> h)::float8 FROM t ORDER BY g <-> h": "SELECT CAST(ST_Distance(g, h) AS double) FROM t ORDER BY ST_Distance(g, h)",
        "SELECT x::int::text FROM t WHERE name ~ 'a&&b' AND (g ~= h::geometry) IS NOT NULL": "SELECT CAST(CAST(x AS int) AS string) FROM t WHERE regexp_like(name, 'a&&b') AND ST_BBoxSame(g, h) IS NOT NULL",
        "SELECT array_agg(a::text ORDER BY b::int), c ~ d, e @ f FROM t -- a && b": "SELECT array_agg(CAST(a AS string) ORDER BY CAST(b AS int)), ST_BBoxContains(c, d), ST_BBoxWithin(e, f) FROM t -- a && b",
        "SELECT CAST((a && b) AS int) IS NULL": "SELECT CAST(ST_BBoxOverlaps(a, b) AS int) IS NULL",
    }
    for text, wanted in cases.items():
        assert to_spark_sql(text) == wanted
        assert to_spark_sql(wanted) == wanted
