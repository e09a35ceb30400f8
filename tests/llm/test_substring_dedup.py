import hashlib
import random

from querygrade.llm.substring_dedup import op1_substring_dedup, repeat_lengths, substring_dedup


def brute(rows, window):
    """Windows against all smaller ids, by definition."""
    first = {}
    words = [(i, (t or "").encode().split()) for i, t in rows]
    for i, w in words:
        if i is None:
            continue
        for s in range(len(w) - window + 1):
            k = tuple(w[s : s + window])
            first[k] = min(first.get(k, i), i)
    out = []
    for i, w in words:
        keep = [True] * len(w)
        for s in range(len(w) - window + 1):
            if i is not None and first[tuple(w[s : s + window])] < i:
                keep[s : s + window] = [False] * window
        out.append((i, len(w), len(w) - sum(keep), hashlib.sha256(b" ".join(x for x, k in zip(w, keep) if k)).hexdigest()))
    return sorted(out, key=str)


def test_random_texts_with_shared_passages(spark):
    rng = random.Random(3)
    shared = [" ".join(rng.choice("abcd") + str(rng.randrange(9)) for _ in range(rng.randrange(6, 60))) for _ in range(8)]
    rows = []
    for i in range(120):
        parts = [" ".join(rng.choice("xyz") + str(rng.randrange(30)) for _ in range(rng.randrange(0, 20)))]
        for _ in range(rng.randrange(0, 4)):
            s = rng.choice(shared).split()
            a = rng.randrange(0, len(s))
            parts += [" ".join(s[a:]) if rng.random() < 0.4 else " ".join(s), rng.choice(["", "q w\te\x0br"])]
        rows.append((i, " ".join(parts)))
    rows += [(200, None), (201, ""), (202, "one"), (203, "r " * 90), (204, "r " * 90), (205, rows[3][1]), (206, rows[3][1]), (206, rows[3][1]), (None, rows[3][1]), (None, None)]
    for window in (6, 7, 12):
        df = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, lo string, half int").repartition(5)
        got = sorted(((r.doc_id, r.n_words, r.n_removed, hashlib.sha256(r.kept_text.encode()).hexdigest()) for r in substring_dedup(df, window).collect()), key=str)
        assert got == brute(rows, window)


def test_empty_table(spark):
    assert substring_dedup(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_levels_end(spark):
    words = [f"w{i}" for i in range(30)]
    df = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(["z", *words])), (3, " ".join(words[:9]))], "doc_id long, text string")
    assert [(r.n_words, r.n_spans) for r in repeat_lengths(df, 8).collect()] == [(8, 48), (16, 30)]


def test_query_against_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert sorted(map(tuple, op1_substring_dedup(spark, sf).collect()), key=str) == brute(rows, 50)
