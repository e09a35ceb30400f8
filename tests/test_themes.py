"""Distances and silhouettes by blocks against brute force."""

import random
import time

import pytest
from pyspark.sql import functions as F

from querygrade.operators.themes import label_silhouette, pairwise_distance, silhouette

SHAPE = "id long, v array<double>, label int"


def _rows(n: int, width: int = 5):
    rnd = random.Random(3)
    rows = [(k, [rnd.gauss(0, 1) for _ in range(width)], k % 4 if k % 17 else None) for k in range(n)]
    rows += [(n + k, rows[k][1], 9) for k in range(3)]  # copies
    rows += [(n + 10, None, 1), (n + 11, [1.0, None, 0.0, 0.0, 0.0], 1), (n + 12, [1.0], 2), (None, [0.0] * width, 1), (5, [0.5] * width, 1), (n + 13, [2e-9] * width, 3), (n + 14, [1e-9] * width, 3)]
    return rows


def _distance(a, b):
    if a is None or b is None or len(a) != len(b) or None in a or None in b:
        return None
    return sum((x - y) ** 2 for x, y in zip(a, b)) ** 0.5


@pytest.mark.parametrize("block_bytes", [40 * 7, 1 << 20])
def test_distances_of_blocks(spark, block_bytes):
    rows = [r for r in _rows(60) if r[0] is not None]
    df = spark.createDataFrame(_rows(60), SHAPE).repartition(3)
    key = lambda r: (r[0], r[1], -1.0 if r[2] is None else round(r[2], 12))
    want = [(a[0], b[0], _distance(a[1], b[1])) for a in rows for b in rows if a[0] < b[0]]
    assert sorted(map(key, pairwise_distance(df, block_bytes=block_bytes).collect())) == sorted(map(key, want))
    want = [(a[0], b[0], _distance(a[1], b[1])) for a in rows for b in rows if a[0] % 10 == 0 and a[0] != b[0]]
    assert sorted(map(key, pairwise_distance(df, df.where("id % 10 = 0"), block_bytes).collect())) == sorted(map(key, want))


@pytest.mark.parametrize("block_bytes", [40 * 7, 1 << 20])
def test_silhouette_of_blocks_equals_that_of_distances(spark, block_bytes):
    df = spark.createDataFrame([r for r in _rows(60) if r[0] != 5], SHAPE)
    slow = silhouette(pairwise_distance(df), df.select("id", "label")).where("id is not null")
    got, want = ({r.id: (r.label, round(r.s, 9)) for r in x.collect()} for x in (label_silhouette(df, block_bytes), slow))
    assert got == want and len(got) > 60


def test_word_vectors_are_learnt_in_parallel(spark, monkeypatch):
    from pyspark.ml import feature

    from querygrade.operators.themes import word_vectors

    seen, fit = [], feature.Word2Vec.fit
    monkeypatch.setattr(feature.Word2Vec, "fit", lambda self, *args: (seen.append(self.getNumPartitions()), fit(self, *args))[1])
    docs = spark.createDataFrame([(k, "alpha beta the gamma" if k else "") for k in range(40)], "id long, text string")
    got = {r.id: r.v for r in word_vectors(docs, 4).collect()}
    assert seen == [spark.sparkContext.defaultParallelism] and sorted(got) == list(range(40)) and got[0] == [0.0] * 4 and any(got[1])


def test_silhouette_of_thousands_of_rows_is_quick(spark):
    df = spark.range(12000).select("id", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda k: F.sin((F.col("id") + 1) * (k + 1.7))).alias("v"), (F.col("id") % 10).cast("int").alias("label"))
    began = time.time()
    assert label_silhouette(df).count() == 12000
    assert time.time() - began < 120  # all pairs as rows take many minutes
