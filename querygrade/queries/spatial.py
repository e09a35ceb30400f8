"""Geometry verdicts, spatial joins and measures on derived geometries."""

from __future__ import annotations

from pyspark.sql import functions as F

from querygrade.functions import geometry_udfs as u
from querygrade.operators.geo_aggregates import centroids, extents, hulls
from querygrade.operators.geo_verdict import geo_verdict
from querygrade.operators.spatial_join import nearest, points_in_boxes, within_distance
from querygrade.queries import query, rounded
from querygrade.sources.tables import table

LON, LAT = "((({k}) * 7919) % 36000) / 100.0 - 180", "((({k}) * 104729) % 17000) / 100.0 - 85"
#: Mutations of a reference geometry and whether the candidate still counts as right.
KINDS = {"identical": 1, "other_srid": 1, "ring_rotated": 1, "ring_reversed": 1, "collinear": 1, "jitter": 1, "shift": 0, "z_near": 1, "z_far": 0, "flat_vs_z": 0, "both_null": 1, "one_null": 0, "invalid": 0, "spaces": 1}
_TEXT_ONLY = ("identical", "both_null", "spaces")
_EXACT = (*_TEXT_ONLY, "ring_rotated", "ring_reversed", "collinear", "z_near", "z_far", "flat_vs_z")  # heights play no part there


def sites(spark, sf, name: str, key: str, shift: int = 0):
    k = f"({key} + {shift})"
    at = lambda text: F.expr(text.format(k=k).replace("100.0", "100.0D"))  # noqa: E731  doubles throughout, as in the twin: decimals would settle ties otherwise
    return table(spark, sf, name).select(key, at(LON).alias("x"), at(LAT).alias("y"))


def zones(spark, sf):
    k = F.col("n_nationkey")
    x, y = -180 + 72 * (k % 5), -85 + 34 * F.floor(k / 5)
    return table(spark, sf, "nation").select("n_nationkey", "n_regionkey", x.cast("double").alias("x1"), y.cast("double").alias("y1"), (x + 72).cast("double").alias("x2"), (y + 34).cast("double").alias("y2"))


def geom_pairs(spark, sf):
    """kind, ref, got: boxes around sites, mutated."""
    s = sites(spark, sf, "customer", "c_custkey").where("abs(x) < 170 and abs(y) < 80")
    p = lambda dx, dy, z="": F.concat(F.format_string("%.7f", F.col("x") + dx), F.lit(" "), F.format_string("%.7f", F.col("y") + dy), F.lit(f" {z}" if z else ""))
    ring = lambda *pts: F.concat(F.lit("POLYGON(("), F.concat_ws(", ", *pts), F.lit("))"))
    box = [p(0, 0), p(1, 0), p(1, 1), p(0, 1)]
    ref = ring(*box, box[0])
    line = lambda z: F.concat(F.lit("LINESTRING Z ("), F.concat_ws(", ", p(0, 0, "1"), p(1, 1, z)), F.lit(")"))
    moved = lambda d: [p(dx + d, dy + d) for dx, dy in ((0, 0), (1, 0), (1, 1), (0, 1), (0, 0))]
    none = F.lit(None).cast("string")
    pairs = {
        "identical": (ref, ref), "other_srid": (ref, u.st_transform(ref, F.lit(3857))), "ring_rotated": (ref, ring(*box[2:], *box[:2], box[2])), "ring_reversed": (ref, ring(*[box[0], *box[::-1]])),
        "collinear": (ref, ring(box[0], p(0.5, 0), *box[1:], box[0])), "jitter": (ref, ring(*moved(1e-7))), "shift": (ref, ring(*moved(1e-3))),
        "z_near": (line("2"), line("2.0000001")), "z_far": (line("2"), line("2.001")), "flat_vs_z": (F.concat(F.lit("LINESTRING("), F.concat_ws(", ", p(0, 0), p(1, 1)), F.lit(")")), line("2")),
        "both_null": (none, none), "one_null": (ref, none), "invalid": (ref, F.lit("POLYGON((0 0, 1 1")), "spaces": (ref, F.concat(F.lit("SRID=4326; "), ref)),
    }
    rows = F.array(*[F.struct(F.lit(k).alias("kind"), a.alias("ref"), b.alias("got")) for k, (a, b) in pairs.items()])
    return s.select("c_custkey", F.inline(rows))


_SITES = f"s AS (SELECT c_custkey, CAST({LON.format(k='c_custkey')} AS DOUBLE) AS x, CAST({LAT.format(k='c_custkey')} AS DOUBLE) AS y FROM customer)"
_SUPPLIERS = f"t AS (SELECT s_suppkey, CAST({LON.format(k='s_suppkey + 500000')} AS DOUBLE) AS x2, CAST({LAT.format(k='s_suppkey + 500000')} AS DOUBLE) AS y2 FROM supplier)"
_ZONES = "z AS (SELECT n_nationkey, n_regionkey, -180 + 72 * (n_nationkey % 5) AS x1, -85 + 34 * (n_nationkey // 5) AS y1, -108 + 72 * (n_nationkey % 5) AS x2, -51 + 34 * (n_nationkey // 5) AS y2 FROM nation)"
_KIND_ROWS = ", ".join(f"('{k}', {v})" for k, v in KINDS.items())


@query("geo_pairs_verdict", f"WITH {_SITES}, k AS (SELECT * FROM (VALUES {_KIND_ROWS}) v(kind, ok)) SELECT kind, count(*) AS n, CAST(count(*) * any_value(ok) AS BIGINT) AS n_correct FROM s, k WHERE abs(x) < 170 AND abs(y) < 80 GROUP BY 1")
def geo_pairs_verdict(spark, sf):
    return geo_verdict(geom_pairs(spark, sf)).groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.sum("verdict").cast("long").alias("n_correct"))


@query("geo_ablation", f"WITH {_SITES}, n AS (SELECT count(*) AS n FROM s WHERE abs(x) < 170 AND abs(y) < 80) SELECT 'text' AS rule, {len(_TEXT_ONLY)} * n AS n_correct FROM n UNION ALL SELECT 'exact', {len(_EXACT)} * n FROM n UNION ALL SELECT 'full', {sum(KINDS.values())} * n FROM n")
def geo_ablation(spark, sf):
    pairs = geom_pairs(spark, sf)
    out = None
    for rule in ("text", "exact", "full"):
        one = geo_verdict(pairs.where("kind <> 'other_srid'") if rule != "full" else pairs, rule).agg(F.lit(rule).alias("rule"), F.sum("verdict").cast("long").alias("n_correct"))
        out = one if out is None else out.unionByName(one)
    return out.select("rule", "n_correct")


@query("geo_z_check", "SELECT count(*) AS n, count(*) FILTER (WHERE vec_id % 3 <> 2) AS n_pass FROM embeddings")
def geo_z_check(spark, sf):
    e = table(spark, sf, "embeddings")
    vertex = lambda a, dz=0.0: F.concat_ws(" ", *[(F.round(F.get("embedding", F.lit(a + k)).cast("double") * 100, 4) + (dz if k == 2 else 0.0)).cast("string") for k in range(3)])
    line = lambda dz: F.concat(F.lit("LINESTRING Z ("), vertex(0), F.lit(","), vertex(3), F.lit(","), vertex(6, dz), F.lit(")"))
    got = F.when(F.col("vec_id") % 3 == 0, line(0.0)).when(F.col("vec_id") % 3 == 1, line(1e-7)).otherwise(line(1e-3))
    return e.select(u.z_close(line(0.0), got).alias("ok")).agg(F.count(F.lit(1)).alias("n"), F.count_if("ok").alias("n_pass"))


@query("site_in_zone", f"WITH {_SITES}, {_ZONES} SELECT n_nationkey, count(*) AS n FROM s JOIN z ON x >= x1 AND x < x2 AND y >= y1 AND y < y2 GROUP BY 1")
def site_in_zone(spark, sf):
    return points_in_boxes(sites(spark, sf, "customer", "c_custkey"), zones(spark, sf), 36.0).groupBy("n_nationkey").agg(F.count(F.lit(1)).alias("n"))


def _suppliers(spark, sf):
    return sites(spark, sf, "supplier", "s_suppkey", 500000).withColumnsRenamed({"x": "x2", "y": "y2"})


@query("site_dwithin", f"WITH {_SITES}, {_SUPPLIERS} SELECT s_suppkey, count(*) AS n FROM s JOIN t ON (x - x2) * (x - x2) + (y - y2) * (y - y2) <= 25 GROUP BY 1")
def site_dwithin(spark, sf):
    return within_distance(sites(spark, sf, "customer", "c_custkey"), _suppliers(spark, sf), 5.0).groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("n"))


@query("site_knn", f"WITH {_SITES}, {_SUPPLIERS}, d AS (SELECT c_custkey, s_suppkey, row_number() OVER (PARTITION BY c_custkey ORDER BY sqrt((x - x2) * (x - x2) + (y - y2) * (y - y2)), s_suppkey) AS rank FROM s, t) SELECT c_custkey, CAST(rank AS INTEGER) AS rank, s_suppkey FROM d WHERE rank <= 3")
def site_knn(spark, sf):
    return nearest(sites(spark, sf, "customer", "c_custkey"), _suppliers(spark, sf), "c_custkey", "s_suppkey", 3).select("c_custkey", "rank", "s_suppkey")


@query("track_length", "WITH p AS (SELECT user_id, hour(ts) AS x, value AS y, lag(hour(ts)) OVER w AS px, lag(value) OVER w AS py FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, count(*) AS n_points, round(coalesce(sum(sqrt((x - px) * (x - px) + (y - py) * (y - py))), 0), 4) AS length FROM p GROUP BY 1")
def track_length(spark, sf):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    p = table(spark, sf, "events").select("user_id", "ts", "event_id", F.hour("ts").cast("double").alias("x"), F.col("value").alias("y")).withColumns({"px": F.lag("x").over(w), "py": F.lag("y").over(w)})
    step = F.sqrt((F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py")))
    return rounded(p.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_points"), F.coalesce(F.sum(step), F.lit(0.0)).alias("length")), "length", digits=4)


def _zone_text():
    pt = lambda a, b: F.concat_ws(" ", F.col(a).cast("string"), F.col(b).cast("string"))
    return F.concat(F.lit("POLYGON(("), F.concat_ws(",", pt("x1", "y1"), pt("x2", "y1"), pt("x2", "y2"), pt("x1", "y2"), pt("x1", "y1")), F.lit("))"))


@query("zone_area", "SELECT n_nationkey, 2448.0::DOUBLE AS area, 212.0::DOUBLE AS perimeter FROM nation")
def zone_area(spark, sf):
    return zones(spark, sf).withColumn("g", _zone_text()).select("n_nationkey", u.st_area("g").alias("area"), u.st_perimeter("g").alias("perimeter"))


@query("zone_extent", f"WITH {_ZONES} SELECT n_regionkey, CAST(min(x1) AS DOUBLE) AS x1, CAST(min(y1) AS DOUBLE) AS y1, CAST(max(x2) AS DOUBLE) AS x2, CAST(max(y2) AS DOUBLE) AS y2 FROM z GROUP BY 1")
def zone_extent(spark, sf):
    return zones(spark, sf).groupBy("n_regionkey").agg(F.min("x1").alias("x1"), F.min("y1").alias("y1"), F.max("x2").alias("x2"), F.max("y2").alias("y2"))


@query("zone_hull")
def zone_hull(spark, sf):
    return hulls(zones(spark, sf).withColumn("g", _zone_text()), ["n_regionkey"], "g")


@query("zone_extent_of_shapes", f"WITH {_ZONES} SELECT n_regionkey, CAST(min(x1) AS DOUBLE) AS x1, CAST(min(y1) AS DOUBLE) AS y1, CAST(max(x2) AS DOUBLE) AS x2, CAST(max(y2) AS DOUBLE) AS y2 FROM z GROUP BY 1")
def zone_extent_of_shapes(spark, sf):
    return extents(zones(spark, sf).withColumn("g", _zone_text()), ["n_regionkey"], "g")


@query("zone_centroid", f"WITH {_ZONES} SELECT n_regionkey, round(avg(x1 + 36), 6) AS x, round(avg(y1 + 17), 6) AS y FROM z GROUP BY 1")
def zone_centroid(spark, sf):
    return rounded(centroids(zones(spark, sf).withColumn("g", _zone_text()), ["n_regionkey"], "g"), "x", "y")


@query("udtf_dump_points", f"WITH {_ZONES} SELECT n_nationkey, CAST(5 AS BIGINT) AS n, CAST(2 * x1 + 2 * x2 + x1 AS DOUBLE) AS sum_x FROM z")
def udtf_dump_points(spark, sf):
    from querygrade.functions.registered import register

    register(spark)
    zones(spark, sf).withColumn("g", _zone_text()).createOrReplaceTempView("zone_shapes")
    return spark.sql("SELECT n_nationkey, count(*) AS n, sum(p.x) AS sum_x FROM zone_shapes, LATERAL dump_points(g) p GROUP BY n_nationkey")


@query("zone_relations", f"WITH {_ZONES}, p AS (SELECT a.n_nationkey AS a, b.n_nationkey AS b, greatest(abs(a.x1 - b.x1) - 72, 0) AS dx, greatest(abs(a.y1 - b.y1) - 34, 0) AS dy FROM z a JOIN z b USING (n_regionkey)) SELECT a, b, dx = 0 AND dy = 0 AS meets, NOT (dx = 0 AND dy = 0) AS apart, a <> b AND dx = 0 AND dy = 0 AS touches, round(sqrt(dx * dx + dy * dy), 6) AS distance FROM p")
def zone_relations(spark, sf):
    z = zones(spark, sf).withColumn("g", _zone_text())
    a, b = (z.select("n_regionkey", F.col("n_nationkey").alias(k), F.col("g").alias(f"g{k}")) for k in "ab")
    return rounded(a.join(b, "n_regionkey").select("a", "b", u.st_intersects("ga", "gb").alias("meets"), u.st_disjoint("ga", "gb").alias("apart"), u.st_touches("ga", "gb").alias("touches"), u.st_distance("ga", "gb").alias("distance")), "distance")


@query("site_home_distance", f"WITH {_SITES}, {_ZONES}, d AS (SELECT n_nationkey, greatest(x1 - x, x - x2, 0) AS dx, greatest(y1 - y, y - y2, 0) AS dy FROM s JOIN customer USING (c_custkey) JOIN z ON c_nationkey = n_nationkey) SELECT n_nationkey, count(*) AS n, count(*) FILTER (WHERE dx * dx + dy * dy <= 900) AS near, round(max(sqrt(dx * dx + dy * dy)), 4) AS farthest FROM d GROUP BY 1")
def site_home_distance(spark, sf):
    home = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").alias("n_nationkey"))
    p = sites(spark, sf, "customer", "c_custkey").join(home, "c_custkey").join(zones(spark, sf).select("n_nationkey", _zone_text().alias("g")), "n_nationkey")
    point = F.concat(F.lit("POINT("), F.col("x").cast("string"), F.lit(" "), F.col("y").cast("string"), F.lit(")"))
    d = p.select("n_nationkey", u.st_distance(point, "g").alias("d"), u.st_dwithin(point, "g", F.lit(30.0)).alias("near"))
    return rounded(d.groupBy("n_nationkey").agg(F.count(F.lit(1)).alias("n"), F.count_if("near").alias("near"), F.max("d").alias("farthest")), "farthest", digits=4)
