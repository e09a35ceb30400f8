"""Best-fit packing with certified lower bounds.

Texts become token ids (``token_ids``); a document longer than a sequence is cut into whole sequences
and a rest.  Pieces are dealt into partitions by a hash and each partition is packed by best-fit
decreasing.  Dual-feasible functions over the histogram of lengths bound the number of sequences from
below, for each partition and for the whole; where the count of all partitions meets the bound of the whole,
the packing is certified and final.  Until then full sequences are final.  A partition that meets its own bound is
set aside; those that miss it exchange the pieces of their sequences with gaps, which are dealt anew, into fewer
partitions, and packed again.  When nothing is gained so, the sequences set aside join the exchange, until the whole is certified, one
partition holds all that has gaps, or such a round gains nothing.

The number of partitions follows the number of pieces (``per_partition``), so a task holds a bounded
number of short rows; texts are never shuffled.  Cut pieces of one very long document do not meet: only its
rest is packed with others.

Defined cases: null text is empty; an empty text is its end id alone; repeated rows are packed as often as
they come; rows with a null id are packed too; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, stored, table
from .token_ids import word_ids

CAPACITY = 2048
END_ID = 0
PER_PARTITION = 32_000
PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = PIECE + ", sequence_id long, offset long"


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, added_tokens: bool = False) -> DataFrame:
    """One row for each piece: doc_id, piece, start, length, ids_crc32."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = word_ids(tokenizer_path, added_tokens)
        step = 4 * capacity
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = model.encode(text) + END_ID.to_bytes(4, "little")
                for k, a in enumerate(range(0, len(ids), step)):
                    part = ids[a : a + step]
                    rows.append((doc, k, a // 4, len(part) // 4, zlib.crc32(part)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, PIECE)


def lower_bound(counts: np.ndarray, capacity: int) -> int:
    """Sequences that lengths with these counts need at least: the best of three dual-feasible families.

    f maps lengths so that whatever fits into a sequence sums to ``capacity`` at most; ceil(sum f / capacity)
    is then a bound.  Families: the identity; rounding to multiples of capacity/k; small lengths to nothing
    with their large complements to the whole.
    """
    size = np.flatnonzero(counts)
    if not len(size):
        return 0
    n = counts[size].astype(object)
    best = -(-int((n * size).sum()) // capacity)
    for k in range(1, 9):
        scaled = (k + 1) * size
        # scaled by k so that all stays in whole numbers
        value = np.where(scaled % capacity == 0, size * k, scaled // capacity * capacity)
        best = max(best, -(-int((n * value).sum()) // (capacity * k)))
    for cut in np.unique(np.minimum(size, capacity - size)):
        if 0 < cut <= capacity // 2:
            value = np.where(size > capacity - cut, capacity, np.where(size < cut, 0, size))
            best = max(best, -(-int((n * value).sum()) // capacity))
    return best


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(sequence number, offset) of every length.  Open gaps are stacks by size; a bit mask finds the least that fits."""
    where, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    mask, used = 0, 0
    order = np.argsort(-lengths, kind="stable")
    for k, size in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fits = mask >> size
        if fits:
            gap = size + (fits & -fits).bit_length() - 1
            at = stacks[gap].pop()
            if not stacks[gap]:
                mask &= ~(1 << gap)
        else:
            gap, at, used = capacity, used, used + 1
        where[k], offset[k] = at, capacity - gap
        if gap > size:
            stacks[gap - size].append(at)
            mask |= 1 << (gap - size)
    return where, offset


def _pack(capacity: int, round_no: int):
    """Packs each partition; ``certified`` says that the partition meets its bound, ``full`` that a sequence has no gap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held).combine_chunks()
        lengths = rows.column("length").to_numpy()
        where, offset = best_fit_decreasing(lengths, capacity)
        filled = np.bincount(where, weights=lengths).astype(np.int64)
        certified = len(filled) == lower_bound(np.bincount(lengths, minlength=capacity + 1), capacity)
        base = (round_no << 56) + (TaskContext.get().partitionId() << 32)
        for name, values in (("sequence_id", base + where), ("offset", offset), ("full", filled[where] == capacity), ("certified", np.full(len(lengths), certified))):
            rows = rows.append_column(name, pa.array(values))
        yield from rows.to_batches(max_chunksize=20_000)

    return run


def pack(items: DataFrame, capacity: int = CAPACITY, per_partition: int = PER_PARTITION, max_rounds: int = 8) -> DataFrame:
    """Adds sequence_id and offset to ``items`` (any table of PIECE rows with length <= capacity)."""
    spark = items.sparkSession
    names = [c.split()[0] for c in PIECE.split(", ")]
    counts = np.zeros(capacity + 1, np.int64)
    for r in items.groupBy("length").count().collect():  # capacity rows at most
        counts[r["length"]] = r["count"]
    n, bound, closed, done = int(counts.sum()), lower_bound(counts, capacity), 0, []
    todo, aside, all_in, before = items.select(*names), [], True, None
    schema = PLACED + ", full boolean, certified boolean"
    for round_no in range(1, max_rounds + 1):
        parts = max(1, -(-n // (per_partition * (1 if round_no == 1 else 2))))
        path = fresh_path(spark, f"packed-{round_no}")
        todo.repartition(parts, F.xxhash64("doc_id", "piece", "start", "ids_crc32", F.lit(round_no))).mapInArrow(_pack(capacity, round_no), schema).write.parquet(path)
        packed = spark.read.schema(schema).parquet(path)
        each = packed.groupBy("full", "certified").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("offset") == 0).alias("used")).collect()
        size = {(r["full"], r["certified"]): (r["n"], r["used"]) for r in each}
        closed += sum(used for (full, _), (_, used) in size.items() if full)
        done.append(packed.where("full"))
        met, missed = size.get((False, True), (0, 0)), size.get((False, False), (0, 0))
        aside.append((packed.where("not full and certified"), *met))
        rest = (packed.where("not full and not certified"), *missed)
        total = closed + rest[2] + sum(used for _, _, used in aside)
        ends = all_in and (parts == 1 or (before is not None and total >= before))
        if total <= bound or ends or round_no == max_rounds:
            done += [rest[0], *(df for df, _, _ in aside)]
            break
        # those that missed their bounds among themselves first, all that has gaps when that gains nothing
        all_in = not rest[1] or parts == 1 or (before is not None and total >= before)
        todo, n, before = rest[0].select(*names), rest[1], total
        if all_in:
            for df, more, _ in aside:
                todo, n = todo.unionByName(df.select(*names)), n + more
            aside = []
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return out.select(*names, "sequence_id", "offset")


def pack_documents(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, per_partition: int = PER_PARTITION, added_tokens: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cut = stored(pieces(docs, tokenizer_path, capacity, added_tokens), "pieces")
    whole = cut.where(F.col("length") == capacity).withColumns({"sequence_id": F.monotonically_increasing_id() + F.lit(0), "offset": F.lit(0).cast("long")})
    return pack(cut.where(F.col("length") < capacity), capacity, per_partition).unionByName(whole)


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), default_tokenizer(), added_tokens=True)
