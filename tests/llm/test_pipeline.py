import random

from pyspark.sql import functions as F

import corpus_pipeline
from querygrade.llm.near_documents import near_groups, without_near_copies


def shingles(t, width=5):
    w = (t or "").lower().split()
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def brute(rows, similarity=0.8):
    sets = {i: shingles(t) for i, t in rows if i is not None}
    ids = sorted(i for i in sets if sets[i])
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for k, a in enumerate(ids):
        for b in ids[:k]:
            both = len(sets[a] & sets[b])
            if both >= similarity * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: find(i) for i in ids}


def make_rows(n_dense=0):
    rng = random.Random(9)
    word = lambda: "w" + str(rng.randrange(400))
    rows, base = [], [[word() for _ in range(rng.randrange(30, 200))] for _ in range(25)]
    for i in range(150):
        w = list(rng.choice(base))
        for _ in range(rng.randrange(0, 5)):
            w[rng.randrange(len(w))] = word()
        rows.append((i, " ".join(w)))
    dense = [word() for _ in range(300)]
    for i in range(n_dense):
        w = list(dense)
        for _ in range(rng.randrange(0, 14)):
            w[rng.randrange(len(w))] = word()
        rows.append((1000 + i, " ".join(w)))
    return rows + [(500, None), (501, ""), (502, "one two"), (503, "One TWO"), (None, "one two")]


def test_near_groups_equal_brute_force(spark):
    rows = make_rows(90)
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, root long").repartition(4)
    want = brute(rows)
    got = {r.node: r.root for r in near_groups(df).collect()}
    assert {i: got.get(i, i) for i in want} == want
    left = without_near_copies(df)
    assert left.columns == df.columns and left.count() == len(rows) - sum(i != r for i, r in want.items())
    assert without_near_copies(df.limit(0)).count() == 0


def test_stages_on_small_tables(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes = []
    for name, stage in corpus_pipeline.STAGES[:3]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        sizes.append(out.count())
    assert all(0 < n < docs.count() for n in sizes[1:])
    whole = corpus_pipeline.run(spark, sf)
    assert whole.select("doc_id").distinct().count() <= min(sizes) and whole.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").isEmpty()
