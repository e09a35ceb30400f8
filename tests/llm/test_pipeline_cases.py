from pyspark.sql import functions as F

import corpus_pipeline

DOCS = "doc_id long, text string, n_chars long, n_entities string, __at string, __row long, text_key int, put string, keys int, root string"


def write(spark, path, rows, labels=()):
    spark.createDataFrame([(*r, "e", "mine", 5, 1, "p", 2, "r") for r in rows], DOCS).repartition(2).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(list(labels), "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


def test_nulls_clashing_columns_and_no_labels(spark, tmp_path):
    rows = [(1, "Mail a.b@c.example.com now", 3), (2, "Mail a.b@c.example.com  now", 3), (None, "alone", 1), (3, None, None), (4, "", 0), (5, "some other words here", 7), (5, "some other words here", 7)]
    sf = write(spark, tmp_path, rows)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs.write.parquet(str(tmp_path / name))
        docs = stage(spark, spark.read.parquet(str(tmp_path / name)), sf)
        assert docs.columns == [c.split()[0] for c in DOCS.split(", ")]
        own = docs.select("n_entities", "__at", "__row", "text_key", "put", "keys", "root").distinct().collect()
        assert [tuple(r) for r in own] == [("e", "mine", 5, 1, "p", 2, "r")]
    got = {r.doc_id for r in corpus_pipeline.run(spark, sf).select("doc_id").collect()}
    assert got == {None, 2, 3, 5}


def test_empty_documents(spark, tmp_path):
    assert corpus_pipeline.run(spark, write(spark, tmp_path, [])).count() == 0


def test_pipeline_keeps_what_brute_force_keeps(spark):
    """The rows of each stage are those that its rule keeps, over whole tables."""
    import re

    from tests.llm.test_pipeline import brute

    sf = "/root/testdata/sf0.001"
    toxic = corpus_pipeline.toxicity(spark, spark.read.parquet(f"{sf}/documents.parquet"), sf).select("doc_id", "text").collect()
    groups = {}
    for r in toxic:
        bare = re.sub(r"[\x20\x09-\x0D]", "", r.text or "")
        groups.setdefault(bare, []).append((-len(r.text or ""), r.doc_id, r.text))
    once = [min(g)[1:] for g in groups.values()]
    roots = brute(once)
    want = {i for i, _ in once if roots.get(i, i) == i}
    got = corpus_pipeline.run(spark, sf)
    assert {r.doc_id for r in got.select("doc_id").distinct().collect()} == want
    assert got.groupBy("doc_id", "piece").count().where("count > 1").isEmpty()
    used = got.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.max(F.col("offset") + F.col("length")).alias("top"))
    assert used.where("n <> top or n > 2048").isEmpty()
