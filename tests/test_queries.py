"""Queries against their DuckDB twins on the smallest tables."""

import math

import duckdb
import pytest

from querygrade.queries import load
from querygrade.sources.tables import TABLES, read_answers, write_answers

SF = "/root/testdata/sf0.001"
QUERIES, SQL = load()
QUICK = "pass_at_n stability robustness overall_rank alignment_schema argument_misuse geo_pairs_verdict site_in_zone site_knn error_profile running_means join_asof join_interval stream_session live_leaderboard leaderboard_watermarked exec_results exec_cells unusable_references exec_accuracy exec_error_classes zone_extent_of_shapes zone_centroid zone_relations site_home_distance theme_silhouette binding_coverage distractor_check theme_databases theme_database_violations theme_descriptions schema_questions prompt_rule_strategy insertion_rows name_clusters".split()


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else f"{v:.6g}"
    return str(v)


@pytest.mark.parametrize("name", QUICK)
def test_twin(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    rel = con.execute(SQL[name])
    at = [[d[0] for d in rel.description].index(c) for c in cols]
    assert sorted(tuple(plain(r[c]) for c in cols) for r in df.collect()) == sorted(tuple(plain(r[i]) for i in at) for r in rel.fetchall())


def test_planted_themes_give_eight(spark):
    from pyspark.sql import functions as F

    from querygrade.operators.themes import theme_clusters

    rows = spark.read.parquet(f"{SF}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x, i: x.cast("double") + F.when(i == F.col("vec_id") % 8, 3.0).otherwise(0.0)).alias("v"))
    for few in (rows.where("id < 96"), rows):  # all rows at once, and by centres
        assert [r.k for r in theme_clusters(few).where("chosen = 1").collect()] == [8]


def test_nearest_with_few_and_far_points(spark):
    from querygrade.operators.spatial_join import nearest

    left = spark.createDataFrame([(1, 0.0, 0.0), (2, 9000.0, 1.0), (3, -5.0, 2.0)], "id long, x double, y double")
    right = spark.createDataFrame([(10, 0.0, 5000.0), (11, 1.0, 1.0)], "rid long, x2 double, y2 double")
    got = {(r.id, r.rank): r.rid for r in nearest(left, right, "id", "rid", 3, 1.0).collect()}
    assert got == {(1, 1): 11, (1, 2): 10, (2, 1): 11, (2, 2): 10, (3, 1): 11, (3, 2): 10}
    assert nearest(left, right.limit(0), "id", "rid", 3, 1.0).count() == 0


def test_nearest_among_dense_points_and_copies(spark):
    from querygrade.operators.spatial_join import _meeting_radius, nearest

    # a dense square and a heap of copies beside far points: the first radius follows the density
    spots = [(k, (k * 37 % 211) / 1e3, (k * 53 % 199) / 1e3) for k in range(3000)] + [(5000 + k, 3.0, 3.0) for k in range(500)] + [(9000, 900.0, 10.0), (9001, -700.0, 5.0)]
    asked = [(k, (k * 29 % 197) / 1e3, (k * 31 % 193) / 1e3) for k in range(80)] + [(100, 3.0, 3.0), (101, 880.0, 0.0)]
    left, right = spark.createDataFrame(asked, "id long, x double, y double"), spark.createDataFrame(spots, "rid long, x2 double, y2 double")
    assert _meeting_radius(left, right, 1600.0, 3) < 0.05
    want = {(i, n + 1): r for i, x, y in asked for n, (_, r) in enumerate(sorted((math.sqrt((x - a) ** 2 + (y - b) ** 2), r) for r, a, b in spots)[:3])}
    assert {(r.id, r.rank): r.rid for r in nearest(left, right, "id", "rid", 3).collect()} == want


def test_sites_are_the_doubles_of_the_twin(spark, tmp_path):
    from querygrade.queries.spatial import _SITES, sites

    spark.range(20000).withColumnRenamed("id", "c_custkey").coalesce(1).write.parquet(str(tmp_path / "customer.parquet"))
    con = duckdb.connect()
    con.execute(f"create view customer as select * from '{tmp_path}/customer.parquet/*.parquet'")
    assert sorted(map(tuple, sites(spark, str(tmp_path), "customer", "c_custkey").collect())) == con.execute(f"WITH {_SITES} SELECT * FROM s ORDER BY 1").fetchall()


def test_ranking_scans_the_facts_once(spark):
    plan = QUERIES["overall_rank"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "part.parquet" not in plan and "fact-sums" in plan


def test_answers_round_trip(spark, tmp_path):
    df = spark.createDataFrame([(1, 2, 0, 1, "A\n\"b\""), (1, 3, 0, 1, None)], "model_id long, qid long, variant int, run int, answer string")
    write_answers(df, str(tmp_path / "a"))
    (tmp_path / "a" / "x.json").write_text("not json\n")
    good, bad = read_answers(spark, str(tmp_path / "a"))
    assert sorted(map(tuple, good.collect())) == sorted(map(tuple, df.collect())) and bad.count() == 1


def test_catalogue_samples_come_from_the_tables(spark):
    from querygrade.queries.bank import theme_catalog

    got = {(r.table, r.field): (r.sample1, r.sample2) for r in theme_catalog(spark, SF).collect()}
    con = duckdb.connect()
    for t, f in (("region", "r_name"), ("orders", "o_orderkey"), ("conversations", "role")):
        assert got[t, f] == tuple(map(str, con.execute(f"select min({f}), max({f}) from '{SF}/{t}.parquet'").fetchone()))
    assert got["pages", "geom"] == (None, None) and len(got) == 67


@pytest.mark.parametrize("name", ["catalog_summary", "bank_violations", "stage_hours"])
def test_twin_of_queries_moved_onto_tables(spark, name):
    test_twin(spark, name)


def test_bank_violations_and_faults_read_their_tables(spark):
    for name, path in (("stage_hours", "events.parquet"), ("exec_error_classes", "orders.parquet"), ("spark_function_docs", "documents.parquet")):
        assert path in QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString() + str(QUERIES[name](spark, SF).inputFiles())
    assert any("theme-catalog" in f for f in QUERIES["bank_violations"](spark, SF).inputFiles())


def test_function_names_are_counted_in_texts(spark):
    from querygrade.operators.bank import spark_function_docs

    docs = spark.createDataFrame([(1, "Upper upper, lower_case"), (2, "the UPPER floor"), (3, None)], "doc_id long, text string")
    got = {r.func: r.n_docs for r in spark_function_docs(spark, docs).collect()}
    assert got["upper"] == 2 and got["floor"] == 1 and got["lower"] == 0 and len(got) > 300


def test_every_query_has_a_twin_or_a_reason(spark):
    rows_only = {"bootstrap_difference", "theme_clusters", "word_vectors", "spark_function_docs", "zone_hull", "agg_approx", "page_text"}
    assert set(QUERIES) - set(SQL) == rows_only


def test_plans_keep_python_after_the_text_filter(spark):
    plan = QUERIES["pass_at_n"](spark, SF)._jdf.queryExecution().toString()
    assert "Python" not in plan.split("Physical Plan")[-1] and "CartesianProduct" not in plan


def test_watermark_leaves_out_rows_of_closed_days(spark, tmp_path):
    from querygrade.streaming.board import live_leaderboard

    shape = "user_id long, ts timestamp, event_type string, value double, model_id int"
    for day in ("2024-01-01", "2024-01-20", "2024-01-21", "2024-01-02"):  # a file a trigger, by time of writing
        spark.sql(f"SELECT 1L AS user_id, TIMESTAMP'{day} 10:00:00' AS ts, 'click' AS event_type, 1.0D AS value, 1 AS model_id").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))

    def days(late):
        stream = spark.readStream.schema(shape).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
        return sorted(str(r.day)[8:] for r in live_leaderboard(stream, late).collect())

    assert days(None) == ["01", "02", "20", "21"]
    assert days("2 days") == ["01", "20", "21"]


def test_hulls_of_parts_equal_the_hull_of_all(spark):
    from querygrade.functions import geometry as g
    from querygrade.operators.geo_aggregates import centroids, hulls

    points = [(k % 3, (k * 37) % 101, (k * 53) % 97) for k in range(3000)]
    df = spark.createDataFrame([(k, f"POINT({x} {y})") for k, x, y in points] + [(0, None), (1, "POINT("), (7, None)], "k int, g string").repartition(7)
    got = {r.k: r.hull for r in hulls(df, ["k"], "g", held_groups=2, held_points=16).collect()}
    for k in range(3):
        ring = g.convex_hull([(float(x), float(y)) for kk, x, y in points if kk == k])
        assert sorted(set(g.dump_points(g.parse_text(got[k])))) == sorted(set(ring))
    assert "EMPTY" in got[7]
    mixed = spark.createDataFrame([(1, "POLYGON((0 0,2 0,2 2,0 2,0 0))"), (1, "POLYGON((4 0,5 0,5 2,4 2,4 0))"), (1, "POINT(90 90)"), (2, "POINT(1 2)"), (2, "POINT(3 4)"), (3, None)], "k int, g string")
    at = {r.k: (r.x, r.y) for r in centroids(mixed, ["k"], "g").collect()}
    assert at[1] == pytest.approx(((4 * 1 + 2 * 4.5) / 6, 1.0)) and at[2] == (2.0, 3.0) and at[3] == (None, None)
    assert hulls(df.where("k > 100"), ["k"], "g").count() == 0
