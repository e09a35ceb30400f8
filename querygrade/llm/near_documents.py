"""One document of each group of near duplicates, by SimHash comparison and exact similarity.

Documents are near duplicates when their sets of five-word shingles have a Jaccard similarity of 0.8 or more;
groups are the components of that relation, and the smallest id of a group stays.  Equal sets are one
representative plus its members before anything is compared.  Representatives of up to ``SHORT``
shingles meet by the least shingle hashes of their set, as many as two similar sets cannot both do without; longer ones by
the least shingle hash of each of ``BINS`` bins (at similarity 0.8 a pair misses all of them with probability 0.2^8 at most);
lengths in between do both.

Similarity is computed from the shingle sets, and no pair that met is left out of that but for two bounds that hold for
every similar pair: the sizes of the sets, and the differing bits of their parity sketches (a shingle turns
one of ``PARITY`` bits, so sets that differ in d shingles differ in d bits at most; sets of more than ``PARITY`` shingles fill
that sketch, so theirs has a bit for each shingle where all pairs of a bucket are compared).  Fingerprints only order
the work: first each member of a bucket meets the first one within ``radius`` bits (bit-sliced,
``bit_slices``), a row for each member at most; then the pairs of members that are still in different groups follow, at whatever
distance of their fingerprints.

No task holds a whole hot bucket.  Buckets of over ``hot`` rows are dealt into chunks that all hold the
bucket's least document, links are sought in the chunks, and while a bucket stays hot the round is repeated with one document for each
group found.  What is left is compared in blocks of two chunks of like size classes (sets whose sizes
differ by more than the similarity allows share no block).

Defined cases: texts without words and rows without id belong to no group; of repeated rows of one id the one
with the least digest of its set stands for the id; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bit_slices import bit_planes, lanes_to_bool, near_lanes, small_groups_links
from .common import components, stored, texts_as_bytes
from .simhash import majority_bits, shingle_hashes

WIDTH, SIMILARITY, RADIUS, BINS, SHORT, PARITY, HOT = 5, 0.8, 18, 8, 39, 1024, 2048
#: Slot of the least hashes of short documents; bins have slots 0 to BINS - 1.
PREFIX = BINS


def least_by_bin(hashes: np.ndarray, bins: int = BINS) -> np.ndarray:
    """The least hash of each bin (by its low bits); bins without a hash give -1."""
    out = np.full(bins, np.iinfo(np.uint64).max, np.uint64)
    np.minimum.at(out, (hashes % np.uint64(bins)).astype(np.int64), hashes)
    return out.view(np.int64)


def meeting_keys(hashes: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """(slot, part) of a document's distinct hashes in ascending order."""
    n, out = len(hashes), []
    if n <= SHORT:
        out += [(PREFIX, int(x)) for x in hashes[: n - math.ceil(similarity * n - 1e-9) + 1].view(np.int64)]
    if n >= similarity * SHORT:
        out += [(k, int(x)) for k, x in enumerate(least_by_bin(hashes)) if x != -1]
    return out


def parity_sketch(hashes: np.ndarray, bits: int = PARITY) -> bytes:
    """Bit k is set where an odd number of the hashes fall on k (by high bits, as bins take the low ones)."""
    odd = np.bincount((hashes >> np.uint64(40)).astype(np.int64) % bits, minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def wide_sketch(hashes: np.ndarray) -> bytes | None:
    """The parity sketch with a bit for each hash or more (a power of two); None where ``PARITY`` bits are as many."""
    return parity_sketch(hashes, 1 << (len(hashes) - 1).bit_length()) if len(hashes) > PARITY else None


def _sketches(width: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), texts_as_bytes(batch.column(1)), strict=True):
                hashes = np.unique(shingle_hashes(text, width)) if doc is not None else ()
                if len(hashes):
                    keys = [{"slot": a, "part": b} for a, b in meeting_keys(hashes, similarity)]
                    out.append((doc, majority_bits(hashes), len(hashes), parity_sketch(hashes), keys, xxhash.xxh128_digest(hashes.tobytes()), wide_sketch(hashes)))
            cols = list(zip(*out, strict=True)) if out else [[]] * 7
            prints = pa.array(np.array(cols[1], np.uint64).view(np.int64))
            keys = pa.array(cols[4], pa.list_(pa.struct([("slot", pa.int32()), ("part", pa.int64())])))
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), prints, pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.binary()), keys, pa.array(cols[5], pa.binary()), pa.array(cols[6], pa.binary())], names=["doc_id", "print", "size", "parity", "keys", "whole", "wide"])

    return run


def _folded(sketches: np.ndarray, bits: int) -> np.ndarray:
    """Wide sketches as rows of ``bits`` bits; longer ones are folded, which leaves a bit the parity of all that fall on it."""
    return np.stack([np.bitwise_xor.reduce(np.frombuffer(x, np.uint64).reshape(-1, bits // 64), axis=0) for x in sketches])


def may_be_similar(sizes: np.ndarray, parity: np.ndarray, a: np.ndarray, b: np.ndarray, similarity: float, wide: np.ndarray | None = None) -> np.ndarray:
    """Whether the sets at positions a and b can be similar enough; false only where they cannot.

    ``wide`` holds wide sketches (None for sets without one)."""
    x, y = sizes[a], sizes[b]
    out = np.minimum(x, y) + 1e-6 >= similarity * np.maximum(x, y)
    most = (x + y) * ((1 - similarity) / (1 + similarity)) + 1e-6  # shingles in one of the two sets only
    at = np.flatnonzero(out)
    for k in range(0, len(at), 1 << 16):
        some = at[k : k + (1 << 16)]
        out[some] = np.bitwise_count(parity[a[some]] ^ parity[b[some]]).sum(axis=1, dtype=np.int64) <= most[some]
    if wide is None:
        return out
    at = np.flatnonzero(out)
    held = np.array([0 if x is None else 8 * len(x) for x in wide], np.int64)
    bits = np.minimum(held[a[at]], held[b[at]])
    for n in np.unique(bits[bits > 0]).tolist():
        of_n = at[bits == n]
        for k in range(0, len(of_n), 4096):
            some = of_n[k : k + 4096]
            docs, place = np.unique(np.concatenate([a[some], b[some]]), return_inverse=True)
            rows, (i, j) = _folded(wide[docs], n), np.split(place, 2)
            out[some] = np.bitwise_count(rows[i] ^ rows[j]).sum(axis=1, dtype=np.int64) <= most[some]
    return out


def _least_links(prints: np.ndarray, sizes: np.ndarray, parity: np.ndarray, radius: int, similarity: float, step: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """(child, parent) positions: every member once, with the first member before it that is within ``radius`` and may be similar."""
    n = len(prints)
    parent, rest = np.full(n, -1), np.arange(1, n)
    planes = bit_planes(prints[rest])
    for a in range(0, n - 1, step):
        free = rest[(parent[rest] < 0) & (rest > a)]
        if not len(free):
            break
        if len(free) * 2 < len(rest):
            rest, planes = free, bit_planes(prints[free])
        now = np.arange(a, min(a + step, n - 1))
        q, r = np.nonzero(lanes_to_bool(near_lanes(planes, prints[now], radius), len(rest)))
        fine = (rest[r] > now[q]) & (parent[rest[r]] < 0)
        q, r = now[q[fine]], rest[r[fine]]
        fine = may_be_similar(sizes, parity, q, r, similarity)
        child, first = np.unique(r[fine], return_index=True)  # pairs come by rising q
        parent[child] = q[fine][first]
    child = np.flatnonzero(parent >= 0)
    return child, parent[child]


def _block_pairs(side: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of positions (left before right) inside groups, or between the two sides of a group, a bounded number at once."""
    two = np.maximum.reduceat(side, starts) > 0 if len(starts) else np.zeros(0, bool)
    for s, size in zip(starts[two].tolist(), sizes[two].tolist(), strict=True):
        left, right = (s + np.flatnonzero(side[s : s + size] == k) for k in (0, 1))
        step = max(1, (1 << 18) // max(1, len(right)))
        for a in range(0, len(left), step):
            part = left[a : a + step]
            yield np.repeat(part, len(right)), np.tile(right, len(part))
    starts, sizes = starts[~two], sizes[~two]
    for size in np.unique(sizes):
        first = starts[sizes == size]
        if size <= 64:
            i, j = np.triu_indices(size, 1)
            some = max(1, (1 << 18) // max(1, len(i)))
            for a in range(0, len(first), some):
                yield (first[a : a + some, None] + i).ravel(), (first[a : a + some, None] + j).ravel()
            continue
        step = max(1, (1 << 18) // int(size))
        for s in first.tolist():
            for a in range(0, int(size), step):
                i, j = np.nonzero(np.arange(a, min(a + step, size))[:, None] < np.arange(size)[None, :])
                yield s + a + i, s + j


#: Columns of a row in a block of a bucket.
BLOCK = ["slot", "part", "block", "side", "doc_id", "print", "root", "size", "parity", "wide"]


def _pairs(radius: int, similarity: float, across: bool):
    """Sorted BLOCK rows to pairs of documents: least links of each block, or (across) the pairs of different roots."""

    def of(rows: list[np.ndarray]):
        slot, part, block, side, doc, prints, root, size, parity, wide = rows
        new = np.concatenate([[True], (slot[1:] != slot[:-1]) | (part[1:] != part[:-1]) | (block[1:] != block[:-1])])
        starts = np.flatnonzero(new)
        members = np.diff(np.concatenate([starts, [len(slot)]]))
        if across:
            for left, right in _block_pairs(side, starts, members):
                apart = root[left] != root[right]
                left, right = left[apart], right[apart]
                fine = may_be_similar(size, parity, left, right, similarity, wide)
                yield doc[left[fine]], doc[right[fine]]
            return
        values = prints.view(np.uint64)
        small = np.flatnonzero((members > 1) & (members <= 64))
        for a in range(0, len(small), 4096):
            left, right = small_groups_links(values, starts[small[a : a + 4096]], members[small[a : a + 4096]], radius)
            fine = may_be_similar(size, parity, left, right, similarity)
            left, right = left[fine], right[fine]
            order = np.lexsort((left, right))
            right, first = np.unique(right[order], return_index=True)  # each member once, with the least id near it
            yield doc[left[order][first]], doc[right]
        for g in np.flatnonzero(members > 64):
            at = slice(starts[g], starts[g] + members[g])
            child, parent = _least_links(values[at], size[at], parity[at], radius, similarity)
            yield doc[at][child], doc[at][parent]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            now = [batch.column(i).to_numpy() for i in range(8)]
            now.append(np.frombuffer(b"".join(batch.column(8).to_pylist()), np.uint64).reshape(-1, PARITY // 64))
            now.append(np.array([*batch.column(9).to_pylist(), None], object)[:-1])
            held = now if held is None else [np.concatenate([a, b]) for a, b in zip(held, now, strict=True)]
            if not len(held[0]):
                continue
            last = np.flatnonzero((held[0] != held[0][-1]) | (held[1] != held[1][-1]) | (held[2] != held[2][-1]))
            cut = last[-1] + 1 if len(last) else 0
            for a, b in of([x[:cut] for x in held]) if cut else ():
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])
            held = [x[cut:] for x in held]
        if held is not None and len(held[0]):
            for a, b in of(held):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return run


def _candidates(blocks: DataFrame, radius: int, similarity: float, across: bool) -> DataFrame:
    """a, b of BLOCK rows; a task holds one block at once."""
    ordered = blocks.select(*BLOCK).repartition("slot", "part", "block").sortWithinPartitions("slot", "part", "block", "doc_id")
    found = ordered.mapInArrow(_pairs(radius, similarity, across), "a long, b long")
    return stored(found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "near-candidates")


def _chunked(rows: DataFrame, buckets: DataFrame, hot: int) -> DataFrame:
    """BLOCK rows: buckets of over ``hot`` rows in chunks, with the bucket's least document in each."""
    met = rows.join(buckets, ["slot", "part"]).withColumn("chunks", F.ceil(F.col("n") / F.lit(hot)).cast("long"))
    leads = (F.col("chunks") > 1) & (F.col("doc_id") == F.col("leader"))
    one = F.when(F.col("chunks") > 1, F.pmod(F.xxhash64("doc_id"), F.col("chunks"))).otherwise(F.lit(0).cast("long"))
    every = F.when(leads, F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).otherwise(F.array(one))
    return met.withColumn("block", F.explode(every)).withColumns({"side": F.lit(0), "wide": F.lit(None).cast("binary")})


def _blocked(rows: DataFrame, wide: DataFrame | None, hot: int, similarity: float) -> DataFrame:
    """BLOCK rows of the buckets that hold several roots, with wide sketches: every two members whose sizes may be similar share a block."""
    mixed = rows.groupBy("slot", "part").agg(F.count(F.lit(1)).alias("n"), F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 <> r1").select("slot", "part", "n")
    mixed = stored(mixed, "near-mixed")
    rows = rows.join(mixed, ["slot", "part"])
    rows = rows.join(wide, "doc_id", "left") if wide is not None else rows.withColumn("wide", F.lit(None).cast("binary"))
    whole = rows.where(F.col("n") <= hot).withColumns({"block": F.lit(0).cast("long"), "side": F.lit(0)})
    # sets whose sizes are in the ratio are of one class or of neighbouring ones
    classed = rows.where(F.col("n") > hot).withColumn("class", F.floor(F.log("size") / F.lit(math.log(1.01 / similarity))).cast("int"))
    counts = classed.groupBy("slot", "part", "class").agg(F.ceil(F.count(F.lit(1)) / F.lit(hot)).cast("int").alias("c"))
    parts = stored(counts.groupBy("slot", "part").agg(F.map_from_entries(F.collect_list(F.struct("class", "c"))).alias("chunks")), "near-classes")
    own = F.element_at("chunks", F.col("class"))
    dealt = classed.join(parts, ["slot", "part"]).withColumn("mine", F.pmod(F.xxhash64("doc_id"), own).cast("int"))

    def towards(step: int):
        other = F.element_at("chunks", F.col("class") + step)
        low, k = F.col("class") + min(step, 0), F.lit(max(step, 0) + max(-step, 0))

        def one(h):
            a, b = (F.least(h, F.col("mine")), F.greatest(h, F.col("mine"))) if step == 0 else (F.col("mine"), h) if step > 0 else (h, F.col("mine"))
            side = F.when(F.col("mine") > h, 1).otherwise(0) if step == 0 else F.lit(0 if step > 0 else 1)
            return F.struct(F.xxhash64(low, k, a, b).alias("block"), side.alias("side"))

        return F.when(other.isNotNull(), F.transform(F.sequence(F.lit(0), other - 1), one)).otherwise(F.array().cast("array<struct<block:bigint,side:int>>"))

    split = dealt.withColumn("to", F.explode(F.concat(towards(0), towards(1), towards(-1)))).withColumns({"block": F.col("to.block"), "side": F.col("to.side")})
    return whole.select(*BLOCK).unionByName(split.select(*BLOCK))


def _similar(docs: DataFrame, pairs: DataFrame, width: int, similarity: float) -> DataFrame:
    """The pairs whose shingle sets are similar enough."""
    named = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [np.unique(shingle_hashes(t, width)) for t in texts_as_bytes(batch.column(1))]
            whole = [xxhash.xxh128_digest(x.tobytes()) for x in got]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(whole, pa.binary()), pa.array([x.view(np.int64) for x in got], pa.list_(pa.int64()))], names=["doc_id", "whole", "shingles"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    every = texts.join(named, "doc_id", "left_semi").mapInArrow(sets, "doc_id long, whole binary, shingles array<long>").where(F.size("shingles") > 0)
    held = stored(every.groupBy("doc_id").agg(F.min(F.struct("whole", "shingles")).getField("shingles").alias("shingles")), "shingle-sets")
    left = held.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x"))
    right = held.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").where(both >= F.lit(similarity) * (F.size("x") + F.size("y") - both)).select("a", "b")


def near_groups(docs: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY, radius: int = RADIUS, hot: int = HOT) -> DataFrame:
    """node, root: documents that are in groups of two or more, with the smallest id of their group."""
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    shape = "doc_id long, print long, size long, parity binary, keys array<struct<slot:int,part:long>>, whole binary, wide binary"
    rest = ["print", "size", "parity", "keys", "wide"]
    every = texts.mapInArrow(_sketches(width, similarity), shape)
    sketches = stored(every.groupBy("doc_id").agg(F.min(F.struct("whole", *rest)).alias("s")).select("doc_id", "s.*"), "sketches")
    firsts = sketches.groupBy("whole").agg(F.min("doc_id").alias("a"), F.count(F.lit(1)).alias("n"))
    equal = stored(sketches.select("whole", F.col("doc_id").alias("b")).join(firsts.where("n > 1"), "whole").where("a <> b").select("a", "b"), "near-equal")
    alone = sketches.join(equal.select(F.col("b").alias("doc_id")), "doc_id", "left_anti")
    dealt = alone.select("doc_id", F.explode("keys").alias("k")).select("doc_id", "k.slot", "k.part")
    several = stored(dealt.groupBy("slot", "part").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("leader")).where("n > 1"), "near-buckets")
    met = stored(dealt.join(several.select("slot", "part"), ["slot", "part"]).join(alone.select("doc_id", "print", "size", "parity"), "doc_id"), "sketch-members")

    links, rows, buckets = None, met.withColumn("root", F.col("doc_id")), several
    while True:
        found = stored(_similar(docs, _candidates(_chunked(rows, buckets, hot), radius, similarity, False), width, similarity), "near-links")
        if links is not None and found.isEmpty():
            break
        links = found if links is None else links.unionByName(found)
        groups = components(links).withColumnRenamed("node", "doc_id")
        rooted = met.join(groups, "doc_id", "left").withColumn("root", F.coalesce("root", "doc_id"))
        if not buckets.where(F.col("n") > hot).limit(1).count():
            break
        # hot buckets meet again, by the least document of each group in them
        least = rooted.join(buckets.where(F.col("n") > hot).select("slot", "part"), ["slot", "part"]).groupBy("slot", "part", "root")
        rows = stored(least.agg(F.min(F.struct("doc_id", "print", "size", "parity")).alias("s")).select("slot", "part", "root", "s.*"), "near-least")
        buckets = stored(rows.groupBy("slot", "part").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("leader")).where("n > 1"), "near-buckets")
    wide = alone.where("wide is not null").select("doc_id", "wide")
    more = _similar(docs, _candidates(_blocked(rooted, None if wide.isEmpty() else wide, hot, similarity), radius, similarity, True), width, similarity)
    return components(links.unionByName(stored(more, "near-links")).unionByName(equal))


def without_near_copies(docs: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY, radius: int = RADIUS) -> DataFrame:
    """The rows of ``docs`` but for those whose group holds a smaller id."""
    gone = near_groups(docs, width, similarity, radius).where("node <> root").select(F.col("node").alias("doc_id"))
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
