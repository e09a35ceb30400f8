import random
import zlib
from array import array

import numpy as np
import sentencepiece

from querygrade.llm.sentence_pieces import PieceTable, CrcShift, decode, default_model, encode, encode_digests, encode_words, far_fold, lattice, op9_sentence_pieces, spaced, word_pattern

TEXTS = [None, "", " ", "  a  b ", "a\nb\tc", "日本語 é́ naïve", "</s> <s> x", "▁a ▁", "the thing " * 50, "x" * 300, "Hello, world! 12345 ---- ====", "\x00"]


def test_ids_equal_the_library_and_decode_back(spark):
    model = sentencepiece.SentencePieceProcessor(model_file=default_model())
    df = spark.createDataFrame([(i, t, "w") for i, t in enumerate(TEXTS)], "doc_id long, text string, word string").repartition(3)
    for head in (4, 1000):
        coded = encode(df, default_model(), head=head)
        assert {r.doc_id: r.ids for r in coded.collect()} == {i: model.encode(t or "") for i, t in enumerate(TEXTS)}
    back = {r.doc_id: r.text for r in decode(coded, default_model()).collect()}
    assert back == {i: (t or "").replace("▁", " ") for i, t in enumerate(TEXTS)}
    assert encode(df.limit(0), default_model()).count() == 0


def test_folds_equal_the_rules_in_python(spark):
    table = PieceTable(default_model())
    words = sorted({w for t in TEXTS for w in (x.replace(" ", "▁") for x in word_pattern(True).findall(spaced(t))) if len(w) <= 24} | {"▁" + w for w in "thinking heed ndthing zuereinen oulà éeux qzxv aaaa".split()})
    df = spark.createDataFrame([(w,) for w in words], "word string")
    for method, rule in (("merge", table.merged), ("viterbi", table.viterbi)):
        for r in encode_words(df, table, method).collect():
            ids = []
            for a, b, i in zip(r.cuts, r.cuts[1:], r.ids):
                ids += [i] if i >= 0 else table.spelled(r.word[a - 1 : b - 1])
            assert ids == rule(r.word), (method, r.word)
        edges = lattice(df.selectExpr("word", "1 AS n"), spark.createDataFrame([(p, s, i) for p, (s, i) in table.pieces.items()], "piece string, score double, id int"), table.longest)
        for r in edges.collect():
            cuts, ids = far_fold(r.word, [e.asDict() for e in r.edges], method)
            assert [x for k, i in enumerate(ids) for x in ([i] if i >= 0 else table.spelled(r.word[cuts[k] - 1 : cuts[k + 1] - 1]))] == rule(r.word)


def test_checksums_of_parts_join():
    rng = random.Random(2)
    runs = [[rng.randbytes(rng.choice((0, 1, 4, 900, 70_000))) for _ in range(rng.randrange(1, 6))] for _ in range(60)]
    parts = [x for r in runs for x in r]
    starts = np.cumsum([0] + [len(r) for r in runs[:-1]])
    got = CrcShift().joined(np.array([zlib.crc32(x) for x in parts], np.uint64), np.array([len(x) for x in parts]), starts)
    assert got.tolist() == [zlib.crc32(b"".join(r)) for r in runs]


def test_null_ids_and_repeated_rows(spark):
    df = spark.createDataFrame([(None, "a b"), (1, "a b"), (1, "a b"), (1, None)], "doc_id long, text string")
    assert sorted(len(r.ids) for r in encode(df, default_model()).collect()) == [0, 2, 2, 2]
    assert encode_digests(df, default_model(), head=0).where("round_trip").count() == 4


def test_query_round_trip(spark):
    sf = "/root/testdata/sf0.001"
    model = sentencepiece.SentencePieceProcessor(model_file=default_model())
    got = {r.doc_id: r for r in op9_sentence_pieces(spark, sf).collect()}
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        ids = model.encode(r.text or "")
        assert (got[r.doc_id].n_pieces, got[r.doc_id].ids_crc32, got[r.doc_id].round_trip) == (len(ids), zlib.crc32(array("i", ids).tobytes()), True)
