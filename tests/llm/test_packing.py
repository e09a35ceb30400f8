import random
import zlib

import numpy as np
import pytest

from querygrade.llm.packing import best_fit_decreasing, default_tokenizer, lower_bound, op5_best_fit_packing, pack, pack_documents, pieces


def check(rows, capacity):
    bins = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for off, size in sorted(b):
            assert off == at and size > 0
            at += size
        assert at <= capacity
    return len(bins)


def test_bounds_hold_on_small_cases():
    rng = np.random.default_rng(4)
    for _ in range(60):
        sizes = rng.integers(1, 20, rng.integers(1, 9))

        def fewest(left, bins):
            if not left:
                return len(bins)
            best, seen = 99, set()
            for k in range(len(bins)):
                if bins[k] + left[0] <= 20 and bins[k] not in seen:
                    seen.add(bins[k])
                    best = min(best, fewest(left[1:], [*bins[:k], bins[k] + left[0], *bins[k + 1 :]]))
            return min(best, fewest(left[1:], [*bins, left[0]]))

        exact = fewest(sizes.tolist(), [])
        where, _ = best_fit_decreasing(sizes, 20)
        assert lower_bound(np.bincount(sizes, minlength=21), 20) <= exact <= where.max() + 1


def test_rounds_exchange_and_stay_whole(spark):
    rng = random.Random(1)
    data = [(i, 0, 0, rng.randrange(1, 100), i) for i in range(3000)] + [(7, 0, 0, 50, 7)] * 5 + [(None, 0, 0, 3, 9)]
    df = spark.createDataFrame(data, "doc_id long, piece int, start long, length long, ids_crc32 long")
    got = pack(df, 100, per_partition=400).collect()
    assert sorted((r.doc_id or -1, r.length) for r in got) == sorted((d[0] or -1, d[3]) for d in data)
    lengths = np.array([d[3] for d in data])
    alone = best_fit_decreasing(lengths, 100)[0].max() + 1
    assert lower_bound(np.bincount(lengths, minlength=101), 100) <= check(got, 100) <= alone * 1.01
    assert pack(df.limit(0), 100).count() == 0


def test_pieces_equal_the_library(spark):
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(default_tokenizer())
    model.encode_special_tokens = True
    texts = [None, "", " ", "It's the café's 3rd ½ – “x” don't!!", "ÀÉî ñ ß İstanbul", "é   a\x1cb\x85c", "日本語 text", "<|endoftext|> a", "naïve_word a_b __ 12.5%", "x" * 3000, "word " * 5000, "’s it’s"]
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(texts)], "doc_id long, text string, length string")
    got = {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in pieces(df, default_tokenizer(), 2048).collect()}
    want = {}
    for i, t in enumerate(texts):
        ids = [*model.encode(t or "", add_special_tokens=False).ids, 0]
        for k, a in enumerate(range(0, len(ids), 2048)):
            part = ids[a : a + 2048]
            want[(i, k)] = (a, len(part), zlib.crc32(np.array(part, "<u4").tobytes()))
    assert got == want
    assert pack_documents(df.limit(0), default_tokenizer()).count() == 0


@pytest.mark.parametrize("sf", ["/root/testdata/sf0.001"])
def test_query(spark, sf):
    from tokenizers import Tokenizer

    got = op5_best_fit_packing(spark, sf).collect()
    model = Tokenizer.from_file(default_tokenizer())
    want = {}
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        ids = [*model.encode(r.text or "", add_special_tokens=False).ids, 0]
        for k, a in enumerate(range(0, len(ids), 2048)):
            want[(r.doc_id, k)] = (a, zlib.crc32(np.array(ids[a : a + 2048], "<u4").tobytes()))
    assert {(r.doc_id, r.piece): (r.start, r.ids_crc32) for r in got} == want
    sizes = [r.length for r in got]
    assert check(got, 2048) <= lower_bound(np.bincount(sizes, minlength=2049), 2048) * 1.05
