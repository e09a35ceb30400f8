import numpy as np
from pyspark.sql import functions as F

from querygrade.llm.ball_tree import top_k


def brute(rows, step, k):
    vecs = {i: np.floor(256 * np.array(v)).astype(int) for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v)}
    out = []
    for q in vecs:
        if q % step == 0:
            s = sorted((-int(vecs[q] @ v), i) for i, v in vecs.items() if i != q and len(v) == len(vecs[q]))[:k]
            out += [(q, r, i, -x) for r, (x, i) in enumerate(s, 1)]
    return sorted(out)


def test_shards_ties_and_odd_vectors(spark):
    rng = np.random.default_rng(6)
    rows = [(i, [float(x) for x in rng.normal(size=6).round(2)]) for i in range(700)]
    rows += [(1000 + i, rows[7][1]) for i in range(150)]
    rows += [(2000, None), (2010, [None] * 6), (2020, [float("nan")] * 6), (2030, [float("inf")] + [0.0] * 5), (2040, [1.0, 2.0]), (2050, []), (2060, [0.5] * 2)]
    df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<double>, rank string")
    for shard_rows in (100_000, 150):
        got = sorted(tuple(r) for r in top_k(df, F.col("vec_id") % 10 == 0, 5, shard_rows, 16).collect())
        assert got == brute(rows, 10, 5)
    assert top_k(df.limit(0), F.col("vec_id") % 10 == 0).count() == 0
    twice = spark.createDataFrame([(0, [1.0]), (0, [1.0]), (1, [2.0]), (None, [9.0])], "vec_id long, embedding array<double>")
    assert sorted(tuple(r) for r in top_k(twice, F.col("vec_id") == 0).collect()) == [(0, 1, 1, 256 * 512)] * 2 + [(0, 2, 0, 256 * 256)] * 2
