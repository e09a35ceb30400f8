import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pytest

from querygrade.llm.class_lm import FORMS, ClassModel, Step, blocks, contexts, cut, exchange_clusters, form_of, forms, likelihood, most_frequent, moved, op6_class_lm, unpacked


def brute(rows):
    def toks(t):
        return [*(t or "").encode().lower().split(), None]

    train = Counter()
    for i, t in rows:
        if zlib.crc32(str(i).encode()) % 7 != 2:
            train.update(toks(t))
    n, v = sum(train.values()), len(train)
    return {i: (len(toks(t)), sum(w in train for w in toks(t)), sum(math.log10((train[w] + 1) / (n + v + 1)) for w in toks(t))) for i, t in rows}, n


def test_exchange_finds_planted_classes():
    rng = np.random.default_rng(0)
    groups = np.array([0, *[1 + k % 3 for k in range(30)]])
    rate = np.array([[0, 50, 1, 1], [1, 1, 60, 1], [1, 1, 1, 60], [20, 60, 1, 1]])
    bigrams = rng.poisson(rate[groups][:, groups] / 5.0).astype(float)
    got = exchange_clusters(bigrams, 4)
    assert len({tuple(sorted(np.flatnonzero(got == c))) for c in range(4)} ^ {tuple(sorted(np.flatnonzero(groups == c))) for c in range(4)}) == 0


def test_base_and_model_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.01"
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    want, n = brute(rows)
    got = op6_class_lm(spark, sf).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r.n_tokens, r.n_known) == want[r.doc_id][:2] and r.base_score == pytest.approx(want[r.doc_id][2], abs=1e-6) and r.train_tokens == n
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_probabilities_sum_to_one(spark):
    docs = spark.createDataFrame([(k, "a b c a b " * (k % 4) + "x1 zz.") for k in range(12)], "doc_id long, text string")
    model = ClassModel(docs, classes=4, clustered=3, head=4)
    # after a text's first word: all known words, the end, and the unknown word of every form class
    words = [w for w in "a b c x1 zz.".split()] + ["qq", "q9", "+", "é", "ü", "ñ", "я", "q.", "q,"]
    probe = spark.createDataFrame([(0, "")] + [(k, w) for k, w in enumerate(words, 1)], "doc_id long, text string")
    got = {r.doc_id: r for r in model.score(probe).collect()}
    total = 10 ** got[0].score
    for k, w in enumerate(words, 1):
        total += 10 ** (got[k].score - float(model.step[model.classify(w.encode()), 0]))
    assert total == pytest.approx(1.0, abs=0.08)


def test_edge_cases(spark):
    df = spark.createDataFrame([(1, None, 5), (2, "", 5), (3, "a a b", 5), (3, "a a b", 5), (None, "a", 5)], "doc_id long, text string, score int")
    out = ClassModel(df).score(df).collect()
    assert len(out) == 5 and all(r.score <= 0 for r in out)
    none = ClassModel(df.limit(0)).score(df).collect()
    assert len(none) == 5 and all(r.n_known == 0 and r.score <= 0 for r in none)
    assert ClassModel(df).score(df.limit(0)).count() == 0


def test_every_repeated_word_is_exchanged(spark):
    """Words far beyond the seeds get the class that a plain comparison of likelihoods gives them; rare ones a form class."""
    rng = np.random.default_rng(4)
    pool = [[f"n{k}" for k in range(30)], [f"v{k}" for k in range(30)]]
    text = [" ".join(str(rng.choice(pool[k % 2])) for k in range(40)) for _ in range(120)]
    docs = spark.createDataFrame(list(enumerate([*text, "once9 only"])), "doc_id long, text string")
    model = ClassModel(docs, classes=3, clustered=7)
    got = {bytes(r.word).decode(): (r.c, r.k) for r in model.words.collect()}
    want = Counter(w for t in [*text, "once9 only"] for w in t.split())
    assert {w: c for w, (c, _) in got.items()} == dict(want)
    assert {got["once9"][1], got["only"][1]} == {3 + 4, 3 + 8}
    assert len({got[w][1] for w in pool[0]}) == 1 and len({got[w][1] for w in pool[1]}) == 1 and got["n0"][1] != got["v0"][1]
    assert model.gains == sorted(model.gains)


def test_step_gains_match_the_likelihood():
    rng = np.random.default_rng(5)
    held = rng.poisson(20.0, (4, 10)).astype(float)
    held[:, 5:] = held[:, :5][:, ::-1]  # equal sums on both sides
    ctx, n, starts = np.array([0, 3, 5, 9]), np.array([1.0, 12.0, 10.0, 3.0]), np.array([0])
    c = np.array([13.0])
    best = []
    for k in range(1, 4):
        more = held.copy()
        more[k, ctx] += n
        best.append(likelihood(more))
    assert moved(ctx, n, starts, c, np.array([-1]), Step(held))[0] == 1 + int(np.argmax(best))


def test_cut_and_forms_match_plain_code():
    rng = np.random.default_rng(6)
    letters = ["a", "Z", ".", ",", "7", "+", "ä", "Ä", "œ", "é", "ñ", "¿", "я", "日", " ", "  ", "\t", "\n", "\x0b", "\x0c", "\r", "\x85", "\u00a0", "\u2003"]
    texts = ["".join(rng.choice(letters, rng.integers(0, 40))) for _ in range(3000)] + [None, "", " ", "\n\n", " a", "a ", "a"]
    for column in (pa.array(texts), pa.array(["x y", *texts]).slice(1), pa.array(texts, pa.large_string())):
        at, edge, words = cut(column)
        words = words.to_pylist()
        got = [[words[k] for k in at[a:b]] for a, b in zip(edge[:-1], edge[1:], strict=True)]
        assert got == [(t or "").encode().lower().split() for t in texts]
    broken = [bytes(rng.choice([0xC3, 0xA4, 0xA9, 0xC2, 0xBF, 0x61, 0x2E, 0x35], rng.integers(0, 5)).astype(np.uint8)) for _ in range(3000)]
    every = [*words, *broken, b"", b".", b"A,", b"[", b"{"]
    assert forms(pa.array(every, pa.binary())).tolist() == [form_of(w) for w in every]
    assert len(forms(pa.array([], pa.binary()))) == 0
    assert [len(cut(pa.array(t, pa.string()))[0]) for t in ([], [None], [" "])] == [0, 0, 0]


def test_blocks_keep_every_row(monkeypatch):
    monkeypatch.setattr("querygrade.llm.class_lm.BLOCK", 1000)
    batches = [pa.record_batch([pa.array([f"{k} {j}" for j in range(k)], pa.string())], names=["text"]) for k in range(30)]
    got = list(blocks(iter(batches)))
    assert [t for b in got for t in b.column(0).to_pylist()] == [t for b in batches for t in b.column(0).to_pylist()] and 1 < len(got) < 30
    monkeypatch.setattr("querygrade.llm.class_lm.BLOCK", 100)
    long = pa.record_batch([pa.array(["x" * 90, None, "", *["y" * 40] * 20])], names=["text"])
    got = list(blocks(iter([long.slice(0, 0), long, long.slice(3, 1)])))
    assert [t for b in got for t in b.column(0).to_pylist()] == [*long.column(0).to_pylist(), "y" * 40] and len(got) > 5


def test_only_words_up_to_the_last_count_reach_the_sort(spark):
    rows = [(f"w{k:03}".encode(), c) for k, c in enumerate([70_000, 90_000, 9, 9, 9, 5, 5, 1, 1, 1])]
    words = spark.createDataFrame(rows, "word binary, c long").repartition(3)
    for limit in range(1, 13):
        found = most_frequent(words, limit)
        assert [bytes(r.word) for r in found.collect()] == [w for w, _ in sorted(rows, key=lambda r: (-r[1], r[0]))][:limit]
    plan = most_frequent(words, 4)._jdf.queryExecution().optimizedPlan().toString()
    assert ">= 9)" in plan


def test_contexts_meet_in_packed_rows(spark):
    """Cells by brute force; they travel packed, so the plan explodes and aggregates none and stores rows of many words."""
    rng = np.random.default_rng(7)
    pool = [f"w{k}" for k in range(400)] + ["é", "x.", "7"]
    texts = [" ".join(rng.choice(pool, rng.integers(0, 60))) for _ in range(200)] + [None, "", "once"]
    seeds, classes = {b"": 0, b"w0": 1, b"w1": 2}, 3
    width, want = classes + FORMS, {}
    for text in texts:
        words = (text or "").encode().split()
        near = [0, *(seeds.get(w, classes + form_of(w)) for w in words), 0]
        for k, w in enumerate(words):
            cells = want.setdefault(w, Counter())
            cells[near[k]] += 1
            cells[width + near[k + 2]] += 1
    docs = spark.createDataFrame([(t,) for t in texts], "text string").repartition(5)
    found = contexts(docs, seeds, classes, 2, 5 << 20)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Generate" not in plan and "Aggregate" not in plan
    rows = found.toArrow()
    assert rows.num_rows < len(want) / 4
    got = {}
    for often, part in ((o, rows.filter(pc.equal(rows.column("often"), o))) for o in (True, False)):
        for words, c, size, x in unpacked(part.to_batches()):
            edge = np.cumsum([0, *size])
            for k, w in enumerate(words.to_pylist()):
                assert w not in got and (c[k] >= 2) == often
                got[w] = (int(c[k]), {int(v) & 1023: int(v) >> 10 for v in x[edge[k] : edge[k + 1]]})
    assert got == {w: (n, dict(cells) if n >= 2 else {}) for w, cells in want.items() for n in [sum(v for k, v in cells.items() if k < width)]}


def test_sums_of_short_and_long_words_agree():
    rng = np.random.default_rng(8)
    step = Step(rng.poisson(30.0, (6, 40)).astype(float))
    for size in (np.sort(rng.integers(1, 12, 50))[::-1], rng.integers(1, 12, 50), np.array([40, 3, 1])):
        ctx = np.concatenate([rng.permutation(40)[:k] for k in size])
        n = rng.integers(1, 60, len(ctx)).astype(float)
        starts = np.cumsum(size) - size
        np.testing.assert_allclose(step.sums(ctx, n, starts), np.add.reduceat(step.gains(ctx, n), starts, axis=0), rtol=1e-12)
