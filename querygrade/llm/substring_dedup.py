"""Substring deduplication by level-wise doubling.

Level 1 looks at windows of half the target length.  Of every run of consecutive half windows only
the one with the least hash is kept (the choice depends on the words alone), so a repeated full window
always holds a kept half window that repeats too, and the table has about 2/27 of a row for each word.
Level 2 doubles the half windows that repeat.  All full windows around a kept half window lie in its
neighbourhood; occurrences with equal neighbourhoods form a class, of which only the first document
is doubled into its full windows, and only where a half window has more than one class.  The full
windows (128-bit hashes) then meet, and a window that starts in a document with a smaller id is
removed.  ``repeat_lengths`` carries the doubling on until no candidate survives.

Rows shuffled: kept half windows twice, texts once by document (a reused exchange), edges of repeats.
Hot passages are min-aggregated before the shuffle and joined back with AQE's skew split.

Defined cases: null text has no words and gives ``kept_text`` ''; rows with null ids are judged by no
one and keep all their words; repeated rows with one id never remove each other and are returned as
often as they come; documents shorter than the window are kept; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BoundedCache, fold_pair, stored, table, texts_as_bytes

WINDOW = 50


def _span_hashes(words: np.ndarray, length: int, lane: int = 0) -> np.ndarray:
    """Hashes of all spans of ``length`` words, by doubling and one overlapping step."""
    have, size = words, 1
    while size * 2 <= length:
        have, size = fold_pair(have[:-size], have[size:], lane), size * 2
    if size < length:
        gap = length - size
        have = fold_pair(have[: len(have) - gap], have[gap:], lane)
    return have


def _slide(values: np.ndarray, width: int, pick) -> np.ndarray:
    have, size = values, 1
    while size * 2 <= width:
        have, size = pick(have[:-size], have[size:]), size * 2
    if size < width:
        gap = width - size
        have = pick(have[: len(have) - gap], have[gap:])
    return have


def _hasher() -> BoundedCache:
    return BoundedCache(xxhash.xxh3_64_intdigest, 1 << 18)


def _word_hashes(words: list[bytes], cache: BoundedCache) -> np.ndarray:
    return np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))


def kept_half_windows(halves: np.ndarray, per_window: int) -> np.ndarray:
    """Positions that are least among ``per_window`` consecutive half windows somewhere."""
    least = _slide(halves, per_window, np.minimum)
    pad = np.zeros(per_window - 1, np.uint64)
    return np.nonzero(_slide(np.concatenate([pad, least, pad]), per_window, np.maximum) == halves)[0]


def _anchors(window: int):
    half = window // 2
    per_window = window - half + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _hasher()
        for batch in batches:
            ids, keys, out = batch.column(0).to_pylist(), batch.column(1).to_pylist(), []
            for doc, key, text in zip(ids, keys, texts_as_bytes(batch.column(2)), strict=True):
                words = text.split() if text is not None and doc is not None else []
                n = len(words)
                if n < window:
                    continue
                halves = _span_hashes(_word_hashes(words, cache), half)
                at = kept_half_windows(halves, per_window)
                lo, hi = np.maximum(at - (window - half), 0), np.minimum(at + window, n)
                inner = (at >= window - half) & (at + window <= n)
                around = np.zeros(len(at), np.uint64)
                p = at[inner]
                around[inner] = fold_pair(fold_pair(halves[p - (window - half)], halves[p], 1), halves[np.minimum(p + window - half, n - half)], 1)
                for k in np.nonzero(~inner)[0]:
                    around[k] = xxhash.xxh3_64_intdigest(b"%d " % (at[k] - lo[k]) + b" ".join(words[lo[k] : hi[k]]))
                out.append((doc, key, halves[at].view(np.int64), around.view(np.int64), at, lo, hi))
            if out:
                size = [len(x[4]) for x in out]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.repeat(np.array([x[0] for x in out], np.int64), size)), pa.array(np.repeat(np.array([x[1] for x in out], np.int64), size))]
                    + [pa.array(np.concatenate([x[i] for x in out])) for i in (2, 3)]
                    + [pa.array(np.concatenate([x[i] for x in out]).astype(np.int32)) for i in (4, 5, 6)],
                    names=["doc_id", "text_key", "half", "around", "at", "lo", "hi"],
                )

    return run


def _full_windows(window: int):
    half = window // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _hasher()
        for batch in batches:
            for doc, key, wanted, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(3).to_pylist(), texts_as_bytes(batch.column(2)), strict=True):
                if not wanted or text is None:
                    continue
                hashes = _word_hashes(text.split(), cache)
                n = len(hashes)
                take = np.zeros(n, bool)
                for p in wanted:
                    take[max(0, p - (window - half)) : min(p, n - window) + 1] = True
                starts = np.nonzero(take[: n - window + 1])[0]
                sides = []
                for lane in (0, 1):
                    spans = _span_hashes(hashes, half, lane)
                    sides.append(fold_pair(spans[starts], spans[starts + window - half], lane).view(np.int64))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(starts), doc, np.int64)), pa.array(np.full(len(starts), key, np.int64)), pa.array(sides[0]), pa.array(sides[1]), pa.array(starts.astype(np.int32))], names=["doc_id", "text_key", "wa", "wb", "lo"])

    return run


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for text, spans in zip(texts_as_bytes(batch.column(2)), batch.column(3).to_pylist(), strict=True):
            words = text.split() if text is not None else []
            keep = np.ones(len(words), bool)
            for x in spans or ():
                keep[x["lo"] : x["hi"]] = False
            edges = np.flatnonzero(np.diff(np.concatenate([[1], keep, [1]])))
            left = words if keep.all() else [words[i] for i in np.flatnonzero(keep)]
            rows.append((len(words), len(words) - len(left), [{"lo": int(a), "hi": int(b)} for a, b in edges.reshape(-1, 2)], b" ".join(left).decode()))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0)] + [pa.array([r[i] for r in rows], t) for i, t in ((0, pa.int64()), (1, pa.int64()), (2, pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))), (3, pa.string()))],
            names=["doc_id", "n_words", "n_removed", "removed", "kept_text"],
        )


def repeated_spans(docs: DataFrame, window: int = WINDOW) -> tuple[DataFrame, DataFrame]:
    """(keyed documents, spans to remove): spans(doc_id, text_key, lo, hi) of words, overlaps allowed."""
    if window < 4:
        raise ValueError("window must have 4 words or more")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), F.col("text").cast("string").alias("text"))
    anchors = stored(keyed.mapInArrow(_anchors(window), "doc_id long, text_key long, half long, around long, at int, lo int, hi int"), "half-windows")
    classes = anchors.groupBy("half", "around").agg(F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc"))
    halves = classes.groupBy("half").agg(F.count("*").alias("n_classes"), F.min("first_doc").alias("low"), F.max("last_doc").alias("high")).where("low < high").drop("low", "high")
    repeated = stored(classes.join(halves, "half").where("n_classes > 1 or first_doc < last_doc"), "repeated-half-windows")
    met = anchors.join(repeated, ["half", "around"])
    inside = met.where("first_doc < doc_id").select("doc_id", "text_key", "lo", "hi")
    edge = met.where("first_doc = doc_id and n_classes > 1").groupBy("doc_id", "text_key").agg(F.collect_set("at").alias("at"))
    wanted = keyed.join(edge, ["doc_id", "text_key"], "left").select("doc_id", "text_key", "text", "at")
    full = stored(wanted.mapInArrow(_full_windows(window), "doc_id long, text_key long, wa long, wb long, lo int"), "full-windows")
    first = stored(full.groupBy("wa", "wb").agg(F.min("doc_id").alias("first_doc"), F.max("doc_id").alias("last_doc")).where("first_doc < last_doc"), "repeated-windows")
    again = full.join(first, ["wa", "wb"]).where("first_doc < doc_id").select("doc_id", "text_key", "lo", (F.col("lo") + window).cast("int").alias("hi"))
    return keyed, inside.unionByName(again)


def substring_dedup(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, removed (word spans), kept_text: words joined by one space."""
    keyed, spans = repeated_spans(docs, window)
    per_doc = spans.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))
    ready = keyed.join(per_doc, ["doc_id", "text_key"], "left").select("doc_id", "text_key", "text", "spans")
    return ready.mapInArrow(_cut, "doc_id long, n_words long, n_removed long, removed array<struct<lo:int,hi:int>>, kept_text string")


def repeat_lengths(docs: DataFrame, start: int = WINDOW) -> DataFrame:
    """n_words, n_spans, n_docs: how many spans of start, 2*start, 4*start ... words repeat across documents.

    Spans repeated at one length alone are extended to twice that length, by joining each to the
    repeated span that begins where it ends, until none survive.
    """

    def starts(batches):
        cache = _hasher()
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), texts_as_bytes(batch.column(1)), strict=True):
                words = (text or b"").split()
                if len(words) < start or doc is None:
                    continue
                spans = _span_hashes(_word_hashes(words, cache), start).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(spans), doc, np.int64)), pa.array(np.arange(len(spans), dtype=np.int32)), pa.array(spans)], names=["doc_id", "at", "span"])

    def survivors(spans: DataFrame) -> DataFrame:
        again = spans.groupBy("span").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b")).where("a < b").select("span")
        return stored(spans.join(again, "span").select("doc_id", "at", "span"), "spans")

    spark, length = docs.sparkSession, start
    level = survivors(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).dropDuplicates(["doc_id"]).mapInArrow(starts, "doc_id long, at int, span long"))
    out = spark.createDataFrame([], "n_words int, n_spans long, n_docs long")
    while True:
        n = level.agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("d")).first()
        if not n["n"]:
            return out
        out = out.unionByName(spark.createDataFrame([(length, n["n"], n["d"])], out.schema))
        left, right = level.alias("x"), level.select("doc_id", (F.col("at") - length).alias("at"), F.col("span").alias("tail"))
        level = survivors(left.join(right, ["doc_id", "at"]).select("doc_id", "at", F.xxhash64("span", "tail").alias("span")))
        length *= 2


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))
