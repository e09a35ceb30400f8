"""SentencePiece encoding and decoding over a relational lattice.

A text becomes words that begin with the space mark, and words are cut further where no piece of the model can
lie across (between letters and other characters, where the model's pieces bear that out).  Every distinct word of the
corpus goes through one relational lattice: its substrings of bounded length are exploded, equi-joined to the piece table and
grouped by word again (the words stay where their hash put them, so only distinct words are shuffled).  A
higher-order ``aggregate`` folds each word's edges to its pieces, in one of two ways:

* ``viterbi``: the best sum of scores, for unigram models;
* ``merge``: edges are visited by falling score, leftmost first, and join two adjacent pieces where they can, for
  BPE models, whose ids a sum of scores does not give.

Words longer than ``LONGEST`` have the same lattice, but their edges are folded by a heap in an Arrow function, as an
array of that length is slow to fold.  Characters without a piece become byte pieces, so decoding gives back every text.

The codes of the most frequent words (at most ``head``, a bound of what is broadcast) are looked up where texts are read; those of
all other words come by joins on the word and back on the text's row, with checksums of the stretches between
them instead of the ids, so texts are never shuffled.

Defined cases: null text is empty; an empty text has no pieces; repeated rows are encoded each, rows with a null id too; an empty table gives
no rows; extra columns are ignored.
"""

from __future__ import annotations

import heapq
import re
import zlib
from array import array
from collections import Counter
from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import stored, table

MARK = "▁"
HEAD = 196_608
LONGEST = 128
LETTERS = "A-Za-zÀ-ÖØ-öø-ɏ"


class PieceTable:
    """Pieces of a model file with ids and scores, and ids of the bytes."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.pieces: dict[str, tuple[float, int]] = {}
        self.bytes: dict[int, int] = {}
        for i in range(model.get_piece_size()):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                self.bytes[int(piece[3:5], 16)] = i
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                self.pieces[piece] = (model.get_score(i), i)
        self.longest = max(map(len, self.pieces), default=1)
        # whether no piece joins one of LETTERS to another character, but for marks before it
        self.letters_apart = not any(re.search(f"[{LETTERS}][^{LETTERS}]|[^{LETTERS}][{LETTERS}]", p.lstrip(MARK)) for p in self.pieces)
        self.texts = {i: p.encode() for p, (_, i) in self.pieces.items()} | {i: bytes([b]) for b, i in self.bytes.items()}

    def spelled(self, piece: str) -> list[int]:
        return [self.bytes[b] for b in piece.encode()]

    def merged(self, word: str) -> list[int]:
        """Ids of one word: adjacent pairs joined by falling score, leftmost first."""
        n, table = len(word), self.pieces
        end, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        heap: list[tuple[float, int, int]] = []

        def offer(a: int) -> None:
            b = end[a]
            if b < n:
                got = table.get(word[a : end[b]])
                if got is not None:
                    heapq.heappush(heap, (-got[0], a, end[b]))

        for a in range(n - 1):
            offer(a)
        while heap:
            _, a, stop = heapq.heappop(heap)
            if not alive[a] or end[a] >= n or end[end[a]] != stop:
                continue
            b = end[a]
            alive[b] = False
            end[a] = stop
            if stop < n:
                before[stop] = a
            offer(a)
            if before[a] >= 0:
                offer(before[a])
        out, a = [], 0
        while a < n:
            got = table.get(word[a : end[a]])
            out += [got[1]] if got is not None else self.spelled(word[a : end[a]])
            a = end[a]
        return out

    def viterbi(self, word: str, missing: float = -1e6) -> list[int]:
        """Ids of one word with the best sum of scores; a lone character without a piece costs ``missing``."""
        best: list[tuple[float, int]] = [(0.0, 0)]
        for stop in range(1, len(word) + 1):
            options = [(best[a][0] + self.pieces[word[a:stop]][0], a) for a in range(max(0, stop - self.longest), stop) if word[a:stop] in self.pieces]
            best.append(max(options, default=(0, 0), key=lambda x: (x[0], -x[1])) if options else (best[stop - 1][0] + missing, stop - 1))
        cuts, at = [], len(word)
        while at:
            cuts.append(word[best[at][1] : at])
            at = best[at][1]
        return [i for p in reversed(cuts) for i in ([self.pieces[p][1]] if p in self.pieces else self.spelled(p))]

    def decode(self, ids) -> str:
        text = b"".join(map(self.texts.__getitem__, ids)).decode("utf-8", "replace").replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text


def word_pattern(letters_apart: bool) -> re.Pattern:
    """Words of a text that begins with a space, each with the spaces before it."""
    return re.compile(f" *[{LETTERS}]+| *[^{LETTERS} ]+| +" if letters_apart else r" *[^ ]+| +")


def spaced(text: str | None) -> str:
    return " " + (text.replace(MARK, " ") if MARK in text else text) if text else ""


def lattice(words: DataFrame, pieces: DataFrame, longest: int) -> DataFrame:
    """word, n, edges: array<struct<rank, start, stop, id>> of distinct ``words(word, n)``, by falling score (rank = -score), leftmost first."""
    size = F.length("word")
    starts = words.select("word", "n", F.explode(F.sequence(F.lit(1), size)).alias("start"))
    spans = starts.select("word", "n", "start", F.explode(F.sequence(F.col("start") + 1, F.least(size + 1, F.col("start") + longest))).alias("stop"))
    # the piece table is as large as the model's vocabulary; a word's first character stays, so that words without edges do too
    met = spans.withColumn("piece", F.substring("word", F.col("start"), F.col("stop") - F.col("start"))).join(F.broadcast(pieces), "piece", "left").where("id is not null or (start = 1 and stop = 2)")
    edge = F.when(F.col("id").isNotNull(), F.struct((-F.col("score")).alias("rank"), "start", "stop", "id"))
    return met.groupBy("word", "n").agg(F.sort_array(F.collect_list(edge)).alias("edges"))


def _edge(edges: Column, start: Column, stop: Column) -> Column:
    return F.get(F.filter(edges, lambda e: (e["start"] == start) & (e["stop"] == stop)), F.lit(0))


def fold_merge(word: Column, edges: Column) -> Column:
    """Cut positions after joining adjacent pieces by falling score."""

    def step(cuts: Column, e: Column) -> Column:
        at = F.array_position(cuts, e["start"]).cast("int")
        joins = (F.get(cuts, at + 1) == e["stop"]) & (at > 0)
        return F.when(joins, F.concat(F.slice(cuts, 1, at), F.slice(cuts, at + 2, F.size(cuts)))).otherwise(cuts)

    several = F.filter(edges, lambda e: e["stop"] - e["start"] > 1)
    return F.aggregate(several, F.sequence(F.lit(1), F.length(word) + 1), step)


def fold_viterbi(word: Column, edges: Column, missing: float = -1e6) -> Column:
    """Cut positions with the best sum of scores."""
    n = F.length(word)
    start = F.array(F.struct(F.lit(0.0).cast("double").alias("score"), F.lit(0).alias("from")))

    def step(best: Column, stop: Column) -> Column:
        into = F.filter(edges, lambda e: e["stop"] == stop + 1)
        options = F.transform(into, lambda e: F.struct((F.get(best, e["start"] - 1)["score"] - e["rank"]).alias("score"), (-e["start"]).alias("from")))
        top = F.array_max(options)
        alone = F.struct((F.get(best, stop - 1)["score"] + F.lit(missing)).alias("score"), stop.alias("from"))
        return F.array_append(best, F.when(top.isNull(), alone).otherwise(F.struct(top["score"].alias("score"), (-top["from"]).alias("from"))))

    best = F.aggregate(F.sequence(F.lit(1), n), start, step)
    return F.aggregate(F.sequence(F.lit(1), n), F.array(n + 1), lambda cuts, _: F.when(F.get(cuts, F.lit(0)) == 1, cuts).otherwise(F.array_prepend(cuts, F.get(best, F.get(cuts, F.lit(0)) - 1)["from"])))


def far_fold(word: str, edges: list[dict], method: str, missing: float = -1e6) -> tuple[list[int], list[int]]:
    """(cuts, ids) of one long word from the edges of its lattice."""
    n, of = len(word), {(e["start"], e["stop"]): (e["rank"], e["id"]) for e in edges}
    if method == "viterbi":
        into: dict[int, list[int]] = {}
        for a, b in of:
            into.setdefault(b, []).append(a)
        best = [(0.0, 0)] * (n + 2)
        for b in range(2, n + 2):
            best[b] = max(((best[a][0] - of[a, b][0], -a) for a in into.get(b, ())), default=(best[b - 1][0] + missing, 1 - b))
        cuts = [n + 1]
        while cuts[-1] > 1:
            cuts.append(-best[cuts[-1]][1])
        cuts.reverse()
    else:
        after, before = list(range(1, n + 3)), list(range(-1, n + 1))
        alive, heap = [True] * (n + 2), []

        def offer(a: int) -> None:
            if 1 <= a and after[a] <= n and (a, after[after[a]]) in of:
                heapq.heappush(heap, (of[a, after[after[a]]][0], a, after[after[a]]))

        for a in range(1, n):
            offer(a)
        while heap:
            _, a, stop = heapq.heappop(heap)
            if alive[a] and after[a] <= n and after[after[a]] == stop:
                alive[after[a]] = False
                after[a], before[stop] = stop, a
                offer(a)
                offer(before[a])
        cuts = [1]
        while cuts[-1] <= n:
            cuts.append(after[cuts[-1]])
    return cuts, [of[a, b][1] if (a, b) in of else -1 for a, b in pairwise(cuts)]


def encode_words(words: DataFrame, table_: PieceTable, method: str = "merge", longest: int = LONGEST) -> DataFrame:
    """word, n, cuts, ids, edges: the relational lattice of distinct ``words(word)``, folded; missing characters are id -1.

    Words over ``longest`` keep their edges and have no cuts yet.
    """
    rows = [(p, s, i) for p, (s, i) in table_.pieces.items()]
    pieces = words.sparkSession.createDataFrame(rows, "piece string, score double, id int")
    edged = lattice(words if "n" in words.columns else words.withColumn("n", F.lit(0)), pieces, table_.longest)
    near = F.length("word") <= longest
    cut = edged.withColumn("cuts", F.when(near, (fold_merge if method == "merge" else fold_viterbi)(F.col("word"), F.col("edges"))))
    ids = F.transform(F.sequence(F.lit(0), F.size("cuts") - 2), lambda k: F.coalesce(_edge(F.col("edges"), F.get("cuts", k), F.get("cuts", k + 1))["id"], F.lit(-1)))
    return cut.select("word", "n", "cuts", F.when(near, ids).alias("ids"), F.when(~near, F.col("edges")).alias("edges"))


def word_codes(words: DataFrame, pieces: PieceTable, method: str = "merge", longest: int = LONGEST) -> DataFrame:
    """word, n, code (its ids as little-endian 32-bit numbers), whole (decoding gives the word back) of distinct ``words(word, n)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = {p: i for p, (_, i) in pieces.pieces.items()}
        for batch in batches:
            codes, whole = [], []
            for word, cuts, edges in zip(*(batch.column(k).to_pylist() for k in (0, 2, 3)), strict=True):
                if cuts is None:
                    cuts, _ = far_fold(word, edges, method)
                ids = []
                for a, b in pairwise(cuts):
                    piece = word[a - 1 : b - 1]
                    i = table.get(piece)
                    ids += pieces.spelled(piece) if i is None else (i,)
                codes.append(array("i", ids).tobytes())
                whole.append(b"".join(map(pieces.texts.__getitem__, ids)) == word.encode())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(codes, pa.binary()), pa.array(whole, pa.bool_())], names=["word", "n", "code", "whole"])

    cut = encode_words(words, pieces, method, longest).select("word", F.col("n").cast("long"), "cuts", "edges")
    return cut.mapInArrow(run, "word string, n long, code binary, whole boolean")


def word_counts(docs: DataFrame, pattern: re.Pattern) -> DataFrame:
    """word (spaces as marks), n of all texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def flush():
            names = list(held)
            for a in range(0, len(names), 50_000):
                part = names[a : a + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array([w.replace(" ", MARK) for w in part], pa.string()), pa.array([held[w] for w in part], pa.int64())], names=["word", "n"])
            held.clear()

        for batch in batches:
            for text in batch.column(0).to_pylist():
                held.update(pattern.findall(spaced(text)))
            if len(held) > 300_000:
                yield from flush()
        yield from flush()

    # workers have combined their words already; few bytes but much work for each word follow: as many tasks as the session's shuffles have
    dealt = docs.select(F.col("text").cast("string")).mapInArrow(run, "word string, n long").repartition(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), "word")
    return dealt.groupBy("word").agg(F.sum("n").alias("n"))


def least_head_count(counts: DataFrame, head: int) -> int:
    """The least count so that ``head`` words at most reach it; found on sixteen steps for each power of two."""
    step = lambda n: F.floor(F.log2(n) * 16)
    sizes = sorted(((r["s"], r["k"], r["n"]) for r in counts.groupBy(step("n").alias("s")).agg(F.count(F.lit(1)).alias("k"), F.min("n").alias("n")).collect()), reverse=True)  # 1,024 rows at most
    total, least = 0, 1 << 62
    for _, k, n in sizes:
        total += k
        if total > head:
            break
        least = n
    return least


class CrcShift:
    """crc32 of a concatenation from the crc32 and lengths of its parts, for many at once."""

    def __init__(self):
        self.steps: list[np.ndarray] = []
        basis = np.array([zlib.crc32(b"\0", 1 << b) ^ zlib.crc32(b"\0", 0) for b in range(32)], np.uint64)
        # tables of 2^k zero bytes: four of 256 entries, one for each byte of a crc
        for _ in range(44):
            tables = np.zeros((4, 256), np.uint64)
            for byte in range(4):
                for bit in range(8):
                    tables[byte, 1 << bit : 2 << bit] = tables[byte, : 1 << bit] ^ basis[8 * byte + bit]
            self.steps.append(tables)
            basis = self._once(tables, basis)

    @staticmethod
    def _once(tables: np.ndarray, values: np.ndarray) -> np.ndarray:
        out = tables[0][values & np.uint64(255)]
        for byte in (1, 2, 3):
            out = out ^ tables[byte][(values >> np.uint64(8 * byte)) & np.uint64(255)]
        return out

    def joined(self, crcs: np.ndarray, sizes: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """crc32 of each run of parts; runs begin at ``starts``."""
        if not len(starts):
            return np.zeros(0, np.uint64)
        until = np.cumsum(sizes)
        ends = np.append(starts[1:], len(sizes))
        after = np.repeat(until[ends - 1], ends - starts) - until
        out = crcs.astype(np.uint64)
        for k in range(int(after.max()).bit_length()):
            at = np.flatnonzero(after >> k & 1)
            out[at] = self._once(self.steps[k], out[at])
        return np.bitwise_xor.reduceat(out, starts)


def _list_of(rows: list[list], kind: pa.DataType) -> pa.ListArray:
    offsets = np.concatenate([[0], np.cumsum(np.fromiter(map(len, rows), np.int64, len(rows)))])
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array([x for r in rows for x in r], kind))


def _coded(docs: DataFrame, model_path: str, method: str, head: int, ids: bool) -> DataFrame:
    """doc_id, n_words, whole, segs and tails: the stretches of a text's frequent words, and the other words between them.

    Of each its ids as binary, or (not ids) a long that holds its number of bytes and their crc32.
    """
    spark, pieces = docs.sparkSession, PieceTable(model_path)
    pattern = word_pattern(pieces.letters_apart)
    counts = word_counts(docs, pattern)
    codes = stored(word_codes(counts, pieces, method), "piece-codes")
    top = codes.where(F.col("n") >= least_head_count(codes, head)).select("word", "code", "whole").toArrow()  # head rows at most
    names = [w.replace(MARK, " ") for w in top.column("word").to_pylist()]
    known = dict(zip(names, top.column("code").to_pylist(), strict=True))
    bad = {w for w, fine in zip(names, top.column("whole").to_pylist(), strict=True) if not fine}
    shared = spark.sparkContext.broadcast((known, bad))
    kind = pa.binary() if ids else pa.int64()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        of, broken = shared.value
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                part, out = batch.slice(a, 500), []
                for text in part.column(1).to_pylist():
                    text = spaced(text)
                    words = pattern.findall(text)
                    got = list(map(of.get, words))
                    n_words = text.count(" ") if "  " not in text else len(re.findall(" +", text))
                    segs, tails, at = [], [], 0
                    if None in got:
                        for k in [k for k, x in enumerate(got) if x is None]:
                            segs.append(b"".join(got[at:k]))
                            tails.append(words[k].replace(" ", MARK))
                            at = k + 1
                    segs.append(b"".join(got[at:]))
                    row += 1
                    out.append((row, n_words, not broken or broken.isdisjoint(words), segs if ids else [len(x) << 32 | zlib.crc32(x) for x in segs], tails))
                cols = list(zip(*out, strict=True))
                arrays = [pa.array(c, t) for c, t in zip(cols[:3], (pa.int64(), pa.int64(), pa.bool_()), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), *arrays, _list_of(cols[3], kind), _list_of(cols[4], pa.string())], names=["doc_id", "row", "n_words", "whole", "segs", "tails"])

    value = "binary" if ids else "bigint"
    shape = f"doc_id long, row long, n_words long, whole boolean, segs array<{value}>, tails array<string>"
    heads = stored(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, shape), "piece-heads")
    rare = heads.where(F.size("tails") > 0).select("row", F.posexplode("tails").alias("at", "word"))
    short = F.col("code") if ids else F.shiftleft(F.octet_length("code").cast("long"), 32).bitwiseOR(F.crc32("code"))
    met = rare.join(codes.select("word", short.alias("v"), "whole"), "word").groupBy("row").agg(F.sort_array(F.collect_list(F.struct("at", "v"))).alias("t"), F.bool_and("whole").alias("fine"))
    both = heads.drop("tails").join(met.select("row", "fine", F.col("t.v").alias("tails")), "row", "left")
    return both.select("doc_id", "n_words", (F.col("whole") & F.coalesce("fine", F.lit(True))).alias("whole"), "segs", F.coalesce("tails", F.array().cast(f"array<{value}>")).alias("tails"))


def encode(docs: DataFrame, model_path: str, method: str = "merge", head: int = HEAD) -> DataFrame:
    """doc_id, n_words, ids array<int>: the ids of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = []
            for segs, tails in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                parts = [None] * (len(segs) + len(tails))
                parts[::2], parts[1::2] = segs, tails
                got.append(np.frombuffer(b"".join(parts), "<i4"))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(got, pa.list_(pa.int32()))], names=["doc_id", "n_words", "ids"])

    coded = _coded(docs, model_path, method, head, True).select("doc_id", "n_words", "segs", "tails")
    return coded.mapInArrow(run, "doc_id long, n_words long, ids array<int>")


def decode(coded: DataFrame, model_path: str) -> DataFrame:
    """doc_id, text of ``coded(doc_id, ids)``; null ids give null."""
    pieces = PieceTable(model_path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([None if x is None else pieces.decode(x) for x in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return coded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def encode_digests(docs: DataFrame, model_path: str, method: str = "merge", head: int = HEAD) -> DataFrame:
    """doc_id, n_words, n_pieces, ids_crc32 (of little-endian 32-bit ids), round_trip (decoding gives the text back)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shift = CrcShift()
        for batch in batches:
            segs, tails = batch.column(2), batch.column(3)
            n_segs, n_tails = (np.diff(c.offsets.to_numpy()) for c in (segs, tails))
            ends = np.cumsum(n_segs + n_tails)
            starts = ends - n_segs - n_tails
            # a text's stretches and other words in turn: stretch, word, stretch ...
            place = [np.repeat(starts + k, n) + 2 * (np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)) for k, n in ((0, n_segs), (1, n_tails))]
            sizes, crcs = np.zeros(ends[-1] if len(ends) else 0, np.int64), np.zeros(ends[-1] if len(ends) else 0, np.uint64)
            for at, flat in zip(place, (segs.flatten(), tails.flatten()), strict=True):
                values = flat.to_numpy()
                sizes[at], crcs[at] = values >> 32, values & 0xFFFFFFFF
            total = np.add.reduceat(sizes, starts) if len(starts) else sizes
            out = shift.joined(crcs, sizes, starts).astype(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(total // 4), pa.array(out), batch.column(4)], names=["doc_id", "n_words", "n_pieces", "ids_crc32", "round_trip"])

    coded = _coded(docs, model_path, method, head, False).select("doc_id", "n_words", "segs", "tails", "whole")
    return coded.mapInArrow(run, "doc_id long, n_words long, n_pieces long, ids_crc32 long, round_trip boolean")


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op9_sentence_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_pieces, ids_crc32, round_trip of every document."""
    return encode_digests(table(spark, sf_dir, "documents"), default_model())
