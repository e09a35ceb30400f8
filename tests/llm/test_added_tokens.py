import zlib

import numpy as np

import corpus_pipeline
from querygrade.llm.packing import default_tokenizer, op5_best_fit_packing


def test_strings_of_added_tokens_are_the_library_tokens(spark, tmp_path):
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(default_tokenizer())
    texts = ["a <|endoftext|> b", "x<|startoftext|>It's<|endoftext|>", "<|ENDOFTEXT|> a", "é <|endoftext|> 日本", "word " * 3000 + "<|endoftext|> w", "<| endoftext |>", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    want = set()
    for i, t in enumerate(texts):
        ids = [*model.encode(t or "", add_special_tokens=False).ids, 0]
        for k, a in enumerate(range(0, len(ids), 2048)):
            part = ids[a : a + 2048]
            want.add((i, k, a, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    for out in (op5_best_fit_packing(spark, str(tmp_path)), corpus_pipeline.packing(spark, docs, "")):
        assert {(r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in out.collect()} == want
