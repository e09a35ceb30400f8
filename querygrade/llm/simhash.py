"""SimHash near-duplicate detection with bit-sliced comparison.

Each document gets a 64-bit fingerprint of its word shingles.  Only distinct fingerprints are
compared.  With radius r the 64 bits are cut into r+2 parts; two fingerprints within r bits agree on
two parts at least, so they meet in one of C(r+2,2) tables of buckets.  Buckets of one are dropped;
buckets over ``max_bucket`` are dealt again by pigeonhole on their free bits, which bounds what a task
holds by construction.  Within a bucket the comparison is bit-sliced (``bit_slices``) and gives a
spanning forest, never all pairs.  Components of these links come from ``common.components``.

Defined cases: null text counts as empty; a text without words has fingerprint zero and links like any
other; fewer words than a shingle make one shingle; repeated rows are returned as often as they come;
rows with a null id get a fingerprint and a component but never name one; empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .bit_slices import forest, small_groups_links
from .common import components, stored, table, texts_as_bytes

RADIUS = 2
WIDTH = 3
MAX_BUCKET = 8192
SEED = 42


def shingle_hashes(text: bytes | None, width: int) -> np.ndarray:
    """XXH64 of every shingle of a text, in order, repeats included."""
    words = text.lower().split() if text else []
    if not words:
        return np.zeros(0, np.uint64)
    line = b" ".join(words)
    n = len(words)
    if n <= width:
        return np.array([xxhash.xxh64_intdigest(line, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n)) + np.arange(n)
    starts = np.concatenate([[0], ends[:-1] + 1])
    digest = xxhash.xxh64_intdigest
    return np.fromiter([digest(line[a:b], SEED) for a, b in zip(starts[: n - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)], np.uint64, n - width + 1)


def majority_bits(hashes: np.ndarray) -> int:
    """Bit k is set where over half the hashes have it."""
    n = len(hashes)
    if not n:
        return 0
    total = np.zeros(64, np.int64)
    for a in range(0, n, 4096):
        part = np.ascontiguousarray(hashes[a : a + 4096].astype("<u8"))
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits((total * 2 > n).astype(np.uint8), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, print (the fingerprint as a signed long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = np.array([majority_bits(shingle_hashes(t, width)) for t in texts_as_bytes(batch.column(1))], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "print"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, print long")


def _part(col: Column, low: int, high: int) -> Column:
    """Bits low..high-1 of a long."""
    return F.shiftrightunsigned(col, low).bitwiseAND(F.lit((1 << (high - low)) - 1)) if high - low < 64 else col


def _cuts(bits: list[int], parts: int) -> list[list[int]]:
    return [list(map(int, x)) for x in np.array_split(np.array(bits), parts)]


def _masked(col: Column, bits: list[int]) -> Column:
    mask = sum(1 << b for b in bits)
    return col.bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))


def bucketed(prints: DataFrame, radius: int, max_bucket: int) -> DataFrame:
    """slot int, part long, item long: buckets in which all pairs within ``radius`` meet, of two items or more."""
    parts = _cuts(list(range(64)), radius + 2)
    pairs = [sorted(a + b) for a, b in combinations(parts, 2)]
    keys = F.array(*[F.struct(F.lit(i).alias("slot"), _masked(F.col("item"), bits).alias("part")) for i, bits in enumerate(pairs)])
    dealt = prints.select("item", F.explode(keys).alias("k")).select("k.slot", "k.part", "item")
    sizes = stored(dealt.groupBy("slot", "part").agg(F.count("*").alias("n")).where("n > 1"), "bucket-sizes")
    meets = dealt.join(sizes, ["slot", "part"])
    finer = []
    for i, bits in enumerate(pairs):
        free = _cuts([b for b in range(64) if b not in bits], radius + 1)
        finer.append(F.array(*[F.struct(F.lit(1000 + i * (radius + 1) + j).alias("slot"), _masked(F.col("item"), sorted(bits + more)).alias("part")) for j, more in enumerate(free)]))
    pick = F.element_at(F.array(*finer), F.col("slot") + 1)
    hot = meets.where(F.col("n") > max_bucket).select("item", F.explode(pick).alias("k")).select("k.slot", "k.part", "item")
    return meets.where(F.col("n") <= max_bucket).select("slot", "part", "item").unionByName(hot)


def _links(radius: int):
    def of_groups(slot, part, item):
        new = np.concatenate([[True], (slot[1:] != slot[:-1]) | (part[1:] != part[:-1])])
        starts = np.flatnonzero(new)
        sizes = np.diff(np.concatenate([starts, [len(slot)]]))
        prints = item.view(np.uint64)
        small = np.flatnonzero((sizes > 1) & (sizes <= 64))
        for a in range(0, len(small), 4096):
            left, right = small_groups_links(prints, starts[small[a : a + 4096]], sizes[small[a : a + 4096]], radius)
            yield item[left], item[right]
        for g in np.flatnonzero(sizes > 64):
            group = prints[starts[g] : starts[g] + sizes[g]]
            child, parent = forest(group, radius)
            yield group[child].view(np.int64), group[parent].view(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            now = [batch.column(i).to_numpy() for i in range(3)]
            if held is not None:
                now = [np.concatenate([a, b]) for a, b in zip(held, now, strict=True)]
            if not len(now[0]):
                continue
            last = np.flatnonzero((now[0] != now[0][-1]) | (now[1] != now[1][-1]))
            cut = last[-1] + 1 if len(last) else 0
            held = [x[cut:] for x in now]
            if cut:
                for a, b in of_groups(*[x[:cut] for x in now]):
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])
        if held is not None and len(held[0]):
            for a, b in of_groups(*held):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return run


def print_links(prints: DataFrame, radius: int = RADIUS, max_bucket: int = MAX_BUCKET) -> DataFrame:
    """a, b: links that connect all of ``prints(item long)`` within ``radius`` bits."""
    dealt = bucketed(prints, radius, max_bucket).repartition("slot", "part").sortWithinPartitions("slot", "part")
    return dealt.select("slot", "part", "item").mapInArrow(_links(radius), "a long, b long")


def simhash_groups(docs: DataFrame, radius: int = RADIUS, width: int = WIDTH, max_bucket: int = MAX_BUCKET) -> DataFrame:
    """doc_id, print, component_id: the smallest doc_id reachable over links of at most ``radius`` bits."""
    prints = stored(fingerprints(docs, width), "fingerprints")
    firsts = stored(prints.groupBy("print").agg(F.min("doc_id").alias("first_doc")), "print-firsts")
    roots = components(print_links(firsts.select(F.col("print").alias("item")), radius, max_bucket)).withColumnRenamed("node", "print")
    rooted = firsts.join(roots, "print", "left").withColumn("root", F.coalesce("root", "print"))
    least = rooted.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    named = stored(rooted.join(least, "root").select("print", "component_id"), "print-components")
    return prints.join(named, "print").select("doc_id", "print", "component_id")


def hex_print(col: str = "print") -> Column:
    return F.lower(F.lpad(F.hex(F.col(col)), 16, "0"))


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_groups(table(spark, sf_dir, "documents")).select("doc_id", hex_print().alias("fingerprint"), "component_id")
