"""The relational surface that candidates use: one query for each kind of operator."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from querygrade.operators.joins import as_of, interval_join
from querygrade.plans.fixtures import attempts, with_ctes
from querygrade.queries import query, rounded
from querygrade.sources.tables import csv_round_trip, read_answers, shared_folder, table, views, write_answers


def _t(spark, sf, *names):
    return [table(spark, sf, n) for n in names]


@query("scan_parquet", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem WHERE l_quantity > 30 GROUP BY 1, 2")
def scan_parquet(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity > 30").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@query("scan_jsonl_roundtrip", with_ctes("SELECT CAST(model_id AS BIGINT) AS model_id, CAST(qid AS BIGINT) AS qid, CAST(variant AS INTEGER) AS variant, CAST(run AS INTEGER) AS run, answer FROM attempts WHERE family = 'concept'"))
def scan_jsonl_roundtrip(spark, sf):
    path = f"{shared_folder(spark)}/answers-{uuid.uuid4().hex}"
    write_answers(attempts(spark, sf).where("family = 'concept'").select("model_id", "qid", "variant", "run", "answer"), path)
    return read_answers(spark, path)[0]


@query("scan_csv_roundtrip", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, nullif(c_mktsegment, 'BUILDING') AS segment FROM customer")
def scan_csv_roundtrip(spark, sf):
    rows = table(spark, sf, "customer").select("c_custkey", "c_name", "c_nationkey", "c_acctbal", F.nullif(F.col("c_mktsegment"), F.lit("BUILDING")).alias("segment"))
    return csv_round_trip(rows, "customers")


@query("project_filter", "SELECT o_orderkey, round(o_totalprice * 1.1, 4) AS gross FROM orders WHERE o_orderstatus IN ('F', 'P') AND o_totalprice BETWEEN 1000 AND 50000")
def project_filter(spark, sf):
    o = table(spark, sf, "orders").where(F.col("o_orderstatus").isin("F", "P") & F.col("o_totalprice").between(1000, 50000))
    return o.select("o_orderkey", F.round(F.col("o_totalprice") * 1.1, 4).alias("gross"))


@query("predicate_mix", "SELECT CASE WHEN c_mktsegment LIKE 'A%' THEN 'a' WHEN regexp_matches(c_name, '7$') THEN 'seven' ELSE 'rest' END AS k, count(*) AS n FROM customer WHERE c_nationkey IS NOT NULL GROUP BY 1")
def predicate_mix(spark, sf):
    k = F.when(F.col("c_mktsegment").like("A%"), "a").when(F.col("c_name").rlike("7$"), "seven").otherwise("rest")
    return table(spark, sf, "customer").where("c_nationkey IS NOT NULL").groupBy(k.alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("join_inner", "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def join_inner(spark, sf):
    o, c = _t(spark, sf, "orders", "customer")
    return rounded(o.join(c, o["o_custkey"] == c["c_custkey"]).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("total")), "total", digits=2)


@query("join_outer", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def join_outer(spark, sf):
    o, c = _t(spark, sf, "orders", "customer")
    return c.join(o, o["o_custkey"] == c["c_custkey"], "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("join_semi", "SELECT count(*) AS n FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def join_semi(spark, sf):
    o, c = _t(spark, sf, "orders", "customer")
    return c.join(o.where("o_orderstatus = 'F'"), o["o_custkey"] == c["c_custkey"], "left_semi").agg(F.count(F.lit(1)).alias("n"))


@query("join_anti", "SELECT count(*) AS n FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')")
def join_anti(spark, sf):
    p, li = _t(spark, sf, "part", "lineitem")
    return p.join(li.where("l_returnflag = 'R'"), p["p_partkey"] == li["l_partkey"], "left_anti").agg(F.count(F.lit(1)).alias("n"))


@query("join_theta", "SELECT a.n_nationkey, count(*) AS n FROM nation a JOIN supplier s ON s_acctbal > 100 * a.n_nationkey GROUP BY 1")
def join_theta(spark, sf):
    n, s = _t(spark, sf, "nation", "supplier")  # 25 rows on the small side
    return s.join(F.broadcast(n), F.col("s_acctbal") > 100 * F.col("n_nationkey")).groupBy("n_nationkey").agg(F.count(F.lit(1)).alias("n"))


@query("join_range", "SELECT n_nationkey, count(*) AS n FROM part JOIN nation ON p_size BETWEEN 2 * n_nationkey AND 2 * n_nationkey + 3 GROUP BY 1")
def join_range(spark, sf):
    p, n = _t(spark, sf, "part", "nation")
    spread = n.select("n_nationkey", F.explode(F.sequence(2 * F.col("n_nationkey"), 2 * F.col("n_nationkey") + 3)).alias("p_size"))
    return p.join(F.broadcast(spread), "p_size").groupBy("n_nationkey").agg(F.count(F.lit(1)).alias("n"))


_INTERVALS = "a AS (SELECT user_id, min(event_id) AS a1, max(event_id) + 1 AS a2 FROM events GROUP BY 1), b AS (SELECT n_nationkey, n_nationkey * 37 AS b1, n_nationkey * 37 + 50 AS b2 FROM nation)"


@query("join_interval", f"WITH {_INTERVALS} SELECT n_nationkey, count(*) AS n FROM a JOIN b ON a1 < b2 AND b1 < a2 GROUP BY 1")
def join_interval(spark, sf):
    e, n = _t(spark, sf, "events", "nation")
    a = e.groupBy("user_id").agg(F.min("event_id").alias("a1"), (F.max("event_id") + 1).alias("a2"))
    b = n.select("n_nationkey", (F.col("n_nationkey") * 37).alias("b1"), (F.col("n_nationkey") * 37 + 50).alias("b2"))
    return interval_join(a, b, 64).groupBy("n_nationkey").agg(F.count(F.lit(1)).alias("n"))


@query("join_asof", "WITH p AS (SELECT user_id, ts, event_id, value FROM events WHERE event_type = 'purchase'), e AS (SELECT user_id, ts, event_id FROM events WHERE event_type = 'error') SELECT e.event_id, (SELECT arg_max(value, (ts, event_id)) FROM p WHERE p.user_id = e.user_id AND p.ts <= e.ts) AS value FROM e")
def join_asof(spark, sf):
    e = table(spark, sf, "events")
    errors, bought = e.where("event_type = 'error'").select("user_id", "ts", "event_id"), e.where("event_type = 'purchase'")
    return as_of(errors, bought.select("user_id", "ts", "value", "event_id").drop("event_id"), ["user_id"], "ts", "value").select("event_id", "value")


@query("join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON o_custkey = c_custkey) WHERE r <= 2")
def join_lateral(spark, sf):
    o = table(spark, sf, "orders")
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return o.withColumn("r", F.row_number().over(w)).where("r <= 2").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")


@query("join_cross_small", "SELECT r_name, count(*) AS n FROM region CROSS JOIN nation GROUP BY 1")
def join_cross_small(spark, sf):
    r, n = _t(spark, sf, "region", "nation")
    return r.crossJoin(n).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_quantity), 6) AS quantity FROM lineitem GROUP BY 1")
def agg_basic(spark, sf):
    out = table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.avg("l_quantity").alias("quantity"))
    return rounded(rounded(out, "revenue", digits=2), "quantity")


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query("agg_filter", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, bool_and(o_totalprice > 0) AS positive, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS largest FROM orders GROUP BY 1")
def agg_filter(spark, sf):
    return table(spark, sf, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("done"), F.bool_and(F.col("o_totalprice") > 0).alias("positive"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("largest"))


for _kind, _sql in (("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("cube", "CUBE (l_returnflag, l_linestatus)"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):

    def _grouped(spark, sf, kind=_kind):
        li = table(spark, sf, "lineitem")
        grouped = li.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus") if kind == "grouping_sets" else getattr(li, kind)("l_returnflag", "l_linestatus")
        return grouped.agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level"))

    query(f"agg_{_kind}", f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(grouping_id(l_returnflag, l_linestatus) AS INTEGER) AS level FROM lineitem GROUP BY {_sql}")(_grouped)


@query("agg_percentile", "SELECT c_mktsegment, round(quantile_cont(c_acctbal, 0.5), 4) AS median FROM customer GROUP BY 1")
def agg_percentile(spark, sf):
    return rounded(table(spark, sf, "customer").groupBy("c_mktsegment").agg(F.percentile("c_acctbal", 0.5).alias("median")), "median", digits=4)


@query("agg_pivot", "SELECT o_orderstatus, " + ", ".join(f"count(*) FILTER (WHERE year(o_orderdate) = {y}) AS y{y}" for y in (1996, 1997)) + " FROM orders GROUP BY 1")
def agg_pivot(spark, sf):
    out = table(spark, sf, "orders").withColumn("y", F.year("o_orderdate")).groupBy("o_orderstatus").pivot("y", [1996, 1997]).agg(F.count(F.lit(1)))
    return out.select("o_orderstatus", *[F.coalesce(F.col(str(y)), F.lit(0)).alias(f"y{y}") for y in (1996, 1997)])


@query("agg_approx")
def agg_approx(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers"), F.approx_percentile("l_quantity", 0.5).alias("median"))


@query("win_rank", "SELECT s_suppkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)")
def win_rank(spark, sf):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal")
    return rounded(table(spark, sf, "supplier").select("s_suppkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.percent_rank().over(w).alias("p"), F.cume_dist().over(w).alias("c")), "p", "c")


@query("win_lag", "SELECT event_id, lag(value) OVER w AS before, lead(value, 2) OVER w AS later, first_value(value) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2).over(w).alias("later"), F.first("value").over(w).alias("first"))


@query("win_rows", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS s FROM events")
def win_rows(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return rounded(table(spark, sf, "events").select("event_id", F.sum("value").over(w).alias("s")), "s", digits=4)


@query("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS n FROM part")
def win_range(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.count(F.lit(1)).over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 5)).alias("n"))


@query("win_ntile", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS INTEGER) AS q FROM customer")
def win_ntile(spark, sf):
    return table(spark, sf, "customer").select("c_custkey", F.ntile(4).over(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")).alias("q"))


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def topk_global(spark, sf):
    return table(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@query("topk_group", "SELECT p_brand, p_partkey FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
def topk_group(spark, sf):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_brand", "p_partkey")


for _name, _op, _sql in (("union", "union", "UNION ALL"), ("intersect", "intersect", "INTERSECT"), ("except", "subtract", "EXCEPT")):

    def _set(spark, sf, op=_op):
        c, s = _t(spark, sf, "customer", "supplier")
        return getattr(c.select(F.col("c_nationkey").alias("k")).where("k < 20"), op)(s.select(F.col("s_nationkey").alias("k")).where("k > 3"))

    query(f"set_{_name}", f"SELECT c_nationkey AS k FROM customer WHERE c_nationkey < 20 {_sql} SELECT s_nationkey FROM supplier WHERE s_nationkey > 3")(_set)


@query("fn_string", "SELECT p_partkey, lower(trim(p_name)) AS a, regexp_replace(p_type, '[AEIOU]', '', 'g') AS b, split_part(p_brand, '#', 2) AS c, levenshtein(p_brand, p_type) AS d, md5(p_name) AS e FROM part")
def fn_string(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.lower(F.trim("p_name")).alias("a"), F.regexp_replace("p_type", "[AEIOU]", "").alias("b"), F.split_part("p_brand", F.lit("#"), F.lit(2)).alias("c"), F.levenshtein("p_brand", "p_type").alias("d"), F.md5(F.col("p_name").cast("binary")).alias("e"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS d FROM orders")
def fn_date(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.trunc("o_orderdate", "month").alias("m"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("d"))


@query("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, round(power(p_size, 1.5), 4) AS p, round(sin(p_size), 6) AS t FROM part")
def fn_math(spark, sf):
    out = table(spark, sf, "part").select("p_partkey", F.ln("p_retailprice").alias("l"), F.sqrt("p_size").alias("s"), F.pow("p_size", F.lit(1.5)).alias("p"), F.sin("p_size").alias("t"))
    return rounded(rounded(out, "l", "s", "t"), "p", digits=4)


@query("fn_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_inner_product(list_transform(embedding, lambda x: x::DOUBLE), list_transform(embedding, lambda x: x::DOUBLE)), 4) AS norm FROM embeddings")
def fn_array(spark, sf):
    square = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0).cast("double"), lambda s, e: s + e)
    return rounded(table(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), square.alias("norm")), "norm", digits=4)


@query("fn_map", "SELECT user_id, CAST(count(*) FILTER (WHERE event_type = 'view') AS BIGINT) AS views, CAST(count(*) FILTER (WHERE event_type = 'click') AS BIGINT) AS clicks FROM events GROUP BY 1")
def fn_map(spark, sf):
    each = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    held = each.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return held.select("user_id", *[F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0)).alias(f"{k}s") for k in ("view", "click")])


@query("fn_json", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def fn_json(spark, sf):
    return table(spark, sf, "events").groupBy(F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("page_text")
def page_text(spark, sf):
    body = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style|nav|aside)\b.*?</\1>", " "), r"(?s)<[^>]+>", " ")
    return table(spark, sf, "pages").select("page_id", F.trim(F.regexp_replace(body, r"\s+", " ")).alias("text"))


@query("sql_cte", "WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) SELECT n, count(*) AS customers FROM big GROUP BY 1")
def sql_cte(spark, sf):
    views(spark, sf, "orders")
    return spark.sql("WITH big AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) SELECT n, count(*) AS customers FROM big GROUP BY 1")


@query("sql_subquery_scalar", "SELECT count(*) AS n FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
def sql_subquery_scalar(spark, sf):
    views(spark, sf, "part")
    return spark.sql("SELECT count(*) AS n FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")


@query("sql_exists", "SELECT n_name FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey AND s_acctbal > 5000)")
def sql_exists(spark, sf):
    views(spark, sf, "nation", "supplier")
    return spark.sql("SELECT n_name FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey AND s_acctbal > :least)", {"least": 5000})


@query("sql_correlated", "SELECT p_partkey FROM part p WHERE p_retailprice = (SELECT max(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)")
def sql_correlated(spark, sf):
    views(spark, sf, "part")
    return spark.sql("SELECT p_partkey FROM part p WHERE p_retailprice = (SELECT max(p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)")
