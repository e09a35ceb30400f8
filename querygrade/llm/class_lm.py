"""Language-model scores by Brown class-based bigrams.

P(word | previous word) = P(class | previous class) * P(word | class).  The ``clustered`` most frequent words
seed the classes by exact exchange (each word moves to the class that raises the likelihood of the class bigrams
most, until no word moves).  Every other word seen at least ``least`` times is then exchanged in parallel: its
counts beside the classes of seeds and forms are a row of a distributed table, and in each sweep all words move
at once against the broadcast matrix of classes and contexts, their own counts taken out.  So the clustered
vocabulary grows with the corpus.  Rarer words, and unknown ones, belong to a class of their written form, which
gives up a discount as the probability of the unknown word there.  Transitions are smoothed with class frequencies.

All counts are taken over every training document.  Words, counts and classes stay a distributed table: only the
``head`` most frequent words are broadcast, and tokens beyond them meet counts and classes in a join, grouped by
document.  What is collected is bounded by the parameters: head words, clustered^2 bigrams, and matrices of
(classes+forms)^2 cells.

Defined cases: null text is empty; an empty text is its end token; repeated rows are learned from and scored each;
without training rows every token is unknown and the score is that of the uniform fallback; an empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc32_of_id, stored, table

CLASSES, CLUSTERED, LEAST, HEAD, SWEEPS = 48, 1024, 2, 196_608, 3
PULL = 2.0  # weight of class frequencies in transitions
# fixed values: letters that tell written forms apart
FORM_MARKS = tuple(map(frozenset, ("äöüß", "éèêçàâîôûùœ", "ñóíáú¿¡")))
FORMS = 9
BLOCK = 1 << 22  # bytes of text that are cut into tokens at once
DEALT = 1 << 20  # training tokens whose words' contexts meet in one task
CELL = 10  # low bits of a packed cell hold its context, the others its count


def form_of(word: bytes) -> int:
    """Class of a written form: marked letters by group, other scripts, digits, symbols, plain by its end."""
    text = word.decode("utf-8", "replace")
    if not text.isascii():
        for k, marks in enumerate(FORM_MARKS):
            if not marks.isdisjoint(text):
                return k
        return 3
    if any(ch.isdigit() for ch in text):
        return 4
    if not text[:1].isalpha():
        return 5
    return 6 if text[-1] == "." else 7 if text[-1] == "," else 8


def _binary(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a binary column without nulls, one value after another, and the values' edges there."""
    column = column.cast(pa.binary())
    _, edge, data = column.buffers()
    edge = np.frombuffer(edge, np.int32)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int32)
    data = np.frombuffer(data, np.uint8)[edge[0] : edge[-1]] if data is not None else np.zeros(0, np.uint8)
    return data, edge - edge[0]


def _packed(data: np.ndarray, edge: np.ndarray) -> pa.Array:
    """Binary column whose values are the items of ``data`` between two edges."""
    edge = (edge * data.itemsize).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(edge) - 1, [None, pa.py_buffer(edge), pa.py_buffer(np.ascontiguousarray(data))])


_PAIRS = np.zeros(1 << 16, np.uint8)  # two bytes of a marked letter: 1 + its group
for _k, _marks in enumerate(FORM_MARKS):
    _PAIRS[[int.from_bytes(ch.encode(), "big") for ch in _marks]] = 1 + _k


def forms(words: pa.Array) -> np.ndarray:
    """``form_of`` each word of a binary column."""
    data, edge = _binary(words)
    out = np.full(len(words), 5)

    def holding(found: np.ndarray) -> np.ndarray:
        upto = np.zeros(len(found) + 1, np.int32)
        np.cumsum(found, out=upto[1:])
        return upto[edge[1:]] > upto[edge[:-1]]

    some = np.flatnonzero(np.diff(edge))
    first, last = data[edge[some]] | 32, data[edge[some + 1] - 1]
    out[some] = np.where((first < ord("a")) | (first > ord("z")), 5, np.where(last == ord("."), 6, np.where(last == ord(","), 7, 8)))
    out[holding((data >= ord("0")) & (data <= ord("9")))] = 4
    out[holding(data >= 128)] = len(FORM_MARKS)
    pair = np.zeros(len(data), np.uint16)  # a marked letter takes two bytes of UTF-8
    pair[:-1] = data[:-1].astype(np.uint16) << 8 | data[1:]
    pair[edge[some + 1] - 1] = 0  # last bytes begin no letter
    group = _PAIRS[pair]
    for k in reversed(range(len(FORM_MARKS))):
        out[holding(group == k + 1)] = k
    return out


def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches joined until they hold ``BLOCK`` bytes; larger ones are parted between rows."""
    held, size = [], 0
    for batch in batches:
        step = -(-batch.num_rows // max(1, round(batch.nbytes / BLOCK))) or 1
        for part in (batch.slice(a, step) for a in range(0, max(1, batch.num_rows), step)):
            if held and size + part.nbytes > 1.5 * BLOCK:
                yield pa.concat_batches(held)
                held, size = [], 0
                pa.default_memory_pool().release_unused()
            held.append(part)
            size += part.nbytes
    if held:
        yield pa.concat_batches(held)


def cut(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """Lower-cased tokens of a string column: their numbers among the distinct words, the texts' edges there, these words."""
    parts = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    coded = parts.flatten().dictionary_encode()
    at, edge = coded.indices.to_numpy(), parts.offsets.to_numpy()
    edge = edge - edge[0]
    empty = pc.index(coded.dictionary, "").as_py()
    if empty >= 0:  # beside space at a text's ends
        kept = at != empty
        at, edge = at[kept], np.concatenate([[0], np.cumsum(kept)])[edge]
    return at, edge, coded.dictionary.cast(pa.binary())


def places(words: pa.Array, among: pa.Array) -> np.ndarray:
    """Place of each word in another column, -1 where it is missing."""
    return pc.fill_null(pc.index_in(words, value_set=among), -1).to_numpy(zero_copy_only=False).astype(np.int64)


def word_counts(texts: DataFrame) -> DataFrame:
    """word binary, c long over all texts of a one-column frame; an end token per text under the empty word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in blocks(batches):
            at, edge, words = cut(block.column(0))
            n = np.bincount(at, minlength=len(words))
            there = np.flatnonzero(n)
            for a in range(0, len(there), 50_000):
                part = there[a : a + 50_000]
                yield pa.RecordBatch.from_arrays([words.take(pa.array(part)), pa.array(n[part])], names=["word", "c"])
            yield pa.RecordBatch.from_arrays([pa.array([b""], pa.binary()), pa.array([len(edge) - 1], pa.int64())], names=["word", "c"])

    return texts.mapInArrow(run, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


def most_frequent(words: DataFrame, limit: int) -> DataFrame:
    """The ``limit`` words of the highest counts (ties: by the word).  One task sorts them, so the words below the count
    of the last are left out before; else each task would send it ``limit`` words."""
    tally = words.groupBy(F.least("c", F.lit(1 << 16)).alias("c")).agg(F.count(F.lit(1)).alias("n")).collect()  # at most 65,536 rows
    seen, last = 0, 0
    for r in sorted(tally, reverse=True):
        seen, last = seen + r.n, r.c
        if seen >= limit:
            break
    return words.where(F.col("c") >= last).orderBy(F.desc("c"), "word").limit(limit)


def _xlogx(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log(np.maximum(x, 1)), 0.0)


def exchange_clusters(bigrams: np.ndarray, classes: int, sweeps: int = 12) -> np.ndarray:
    """Class of every word (0: the text boundary, alone in class 0) from a matrix of bigram counts."""
    n = len(bigrams)
    of = np.array([0] + [1 + k % (classes - 1) for k in range(n - 1)])
    member = np.zeros((n, classes))
    member[np.arange(n), of] = 1
    pairs = member.T @ bigrams @ member
    right, left = bigrams @ member, bigrams.T @ member  # of each word: counts with classes after and before it
    for _ in range(sweeps):
        moved = 0
        for w in range(1, n):
            a, r, s = of[w], right[w].copy(), left[w].copy()
            own = bigrams[w, w]
            if r.sum() + s.sum() == 0:
                continue
            # take w out of its class
            pairs[a, :] -= r
            pairs[:, a] -= s
            pairs[a, a] += own
            r[a] -= own
            s[a] -= own
            rows, cols = pairs.sum(axis=1), pairs.sum(axis=0)
            gain = (_xlogx(pairs + r[None, :]) - _xlogx(pairs)).sum(axis=1) + (_xlogx(pairs + s[:, None]) - _xlogx(pairs)).sum(axis=0)
            same = np.diag(pairs)
            gain += _xlogx(same + r + s + own) - _xlogx(same + r) - _xlogx(same + s) + _xlogx(same)
            gain -= _xlogx(rows + r.sum() + own) - _xlogx(rows) + _xlogx(cols + s.sum() + own) - _xlogx(cols)
            gain[0] = -np.inf
            b = int(gain.argmax())
            if gain[b] <= gain[a] + 1e-9:
                b = a
            pairs[b, :] += r
            pairs[:, b] += s
            pairs[b, b] += own
            if b != a:
                moved += 1
                of[w] = b
                right[:, a] -= bigrams[:, w]
                right[:, b] += bigrams[:, w]
                left[:, a] -= bigrams[w, :]
                left[:, b] += bigrams[w, :]
        if not moved:
            break
    return of


def seed_pairs(texts: DataFrame, ids: dict[bytes, int]) -> np.ndarray:
    """Square matrix of neighbouring seed words; other words and pairs with them are left out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = pa.array(shared.value, pa.binary())
        held = np.zeros(width * width, np.int64)
        for block in blocks(batches):
            at, edge, words = cut(block.column(0))
            seq = np.insert(places(words, names)[at], edge, 0)
            a, b = seq[:-1], seq[1:]
            fine = (a >= 0) & (b >= 0)
            held += np.bincount(a[fine] * width + b[fine], minlength=len(held))
        pair = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(pair), pa.array(held[pair])], names=["pair", "n"])

    width = len(ids)
    shared = texts.sparkSession.sparkContext.broadcast(list(ids))
    got = texts.mapInArrow(run, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).toArrow()  # at most width^2 rows
    out = np.zeros(width * width)
    out[got.column("pair").to_numpy()] = got.column("n").to_numpy()
    return out.reshape(width, width)


def contexts(texts: DataFrame, seeds: dict[bytes, int], classes: int, least: int, n_tokens: int) -> DataFrame:
    """How often each word stands after (ctx) and before (classes + FORMS + ctx) a class of seeds or forms.

    A row holds up to 4,096 words: the words' bytes and lengths, their counts, how many cells each has, and the cells;
    words seen less than ``least`` times are in rows of their own, without cells."""
    width = classes + FORMS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, seed_class = pa.array(list(shared.value), pa.binary()), np.array([*shared.value.values(), -1])
        for block in blocks(batches):
            at, edge, words = cut(block.column(0))
            near = seed_class[places(words, names)]
            near = np.append(np.where(near >= 0, near, classes + forms(words)), shared.value[b""])
            whole = np.int32 if len(near) * 2 * width < 1 << 31 else np.int64
            seq = np.insert(at.astype(whole), edge, len(words))
            of = near.astype(whole)[seq]
            spot = np.flatnonzero(seq < len(words))
            code = np.concatenate([seq[spot] * (2 * width) + of[spot - 1], seq[spot] * (2 * width) + width + of[spot + 1]])
            code, n = np.unique(code, return_counts=True)
            word, cell = code // (2 * width), code % (2 * width) + (n.astype(np.int64) << CELL)
            first = np.flatnonzero(np.diff(word, prepend=-1))
            edge = np.append(first, len(code))
            for a in range(0, len(first), 10_000):
                b = min(a + 10_000, len(first))
                yield pa.RecordBatch.from_arrays([words.take(pa.array(word[first[a:b]])), _packed(cell[edge[a] : edge[b]], edge[a : b + 1] - edge[a])], names=["word", "x"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [batch for batch in batches if batch.num_rows]
        if not rows:
            return
        rows = pa.concat_batches(rows)
        coded = rows.column(0).dictionary_encode()
        data, edge = _binary(rows.column(1))
        cell = data.view(np.int64)
        key = (np.repeat(coded.indices.to_numpy().astype(np.int64), np.diff(edge) // 8) << CELL) + (cell & mask)
        order = np.argsort(key)
        key, n = key[order], cell[order] >> CELL
        first = np.flatnonzero(np.diff(key, prepend=-1))
        key, n = key[first], np.add.reduceat(n, first)
        starts = np.flatnonzero(np.diff(key >> CELL, prepend=-1))  # every word has cells
        c = np.add.reduceat(np.where(key & mask < width, n, 0), starts)
        size = np.diff(starts, append=len(key))
        cell = (key & mask) + (n << CELL)
        for often in (True, False):
            of = np.flatnonzero((c >= least) == often)
            of = of[np.argsort(-size[of], kind="stable")]  # alike words side by side, see Step.sums
            for a in range(0, len(of), 4096):
                part = of[a : a + 4096]
                data, edge = _binary(coded.dictionary.take(pa.array(part)))
                cells = np.zeros(0, np.int64)
                if often:
                    upto = np.cumsum(size[part])
                    cells = cell[np.arange(upto[-1]) + np.repeat(starts[part] - upto + size[part], size[part])]
                held = [data, np.diff(edge).astype(np.int32), c[part], size[part].astype(np.int32), cells]
                yield pa.RecordBatch.from_arrays([*(pa.array([x.tobytes()], pa.binary()) for x in held), pa.array([often])], names=["words", "lengths", "c", "size", "x", "often"])

    mask = (1 << CELL) - 1
    spark = texts.sparkSession
    shared = spark.sparkContext.broadcast(seeds)
    # a task adds one row of at most 2 * width cells for a word and block of text, so no word makes a heavy key
    parts = max(spark.sparkContext.defaultParallelism, -(-n_tokens // DEALT))
    dealt = texts.mapInArrow(run, "word binary, x binary").repartition(parts, "word")
    return dealt.mapInArrow(merge, "words binary, lengths binary, c binary, size binary, x binary, often boolean")


def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray]]:
    """(words, counts, cells of each word, cells) of each row that ``contexts`` made."""
    for batch in batches:
        for words, lengths, c, size, x in zip(*(column.to_pylist() for column in batch.columns[:5]), strict=True):
            edge = np.concatenate([[0], np.cumsum(np.frombuffer(lengths, np.int32))])
            yield _packed(np.frombuffer(words, np.uint8), edge), np.frombuffer(c, np.int64), np.frombuffer(size, np.int32), np.frombuffer(x, np.int64)


class Step:
    """Counts of the classes beside each context at the start of a sweep, with the gains of small counts worked out."""

    SMALL, SHORT = 32, 12

    def __init__(self, held: np.ndarray):
        self.held = held
        self.total = held[:, : held.shape[1] // 2].sum(axis=1)
        up = np.arange(1, self.SMALL + 1)[:, None, None]
        self.before, self.total_before = _xlogx(held.T), _xlogx(self.total)
        self.quick = _xlogx(held.T + up) - self.before  # count - 1, context, class

    def gains(self, ctx: np.ndarray, n: np.ndarray) -> np.ndarray:
        """(entries, classes) growth of the likelihood's sum over cells."""
        out = self.quick[np.minimum(n, self.SMALL).astype(np.int64) - 1, ctx]
        big = np.flatnonzero(n > self.SMALL)
        if len(big):
            out[big] = _xlogx(self.held.T[ctx[big]] + n[big, None]) - self.before[ctx[big]]
        return out

    def sums(self, ctx: np.ndarray, n: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """(words, classes) gains of each word's entries, added from the first to the last."""
        size = np.diff(starts, append=len(ctx))
        if size[0] > self.SHORT or (np.diff(size) > 0).any():
            return np.add.reduceat(self.gains(ctx, n), starts, axis=0)
        out = self.gains(ctx[starts], n[starts])
        for k in range(1, size[0]):  # words with fewer entries come last
            at = starts[: np.count_nonzero(size > k)] + k
            out[: len(at)] += self.gains(ctx[at], n[at])
        return out


def moved(ctx: np.ndarray, n: np.ndarray, starts: np.ndarray, c: np.ndarray, now: np.ndarray, step: Step) -> np.ndarray:
    """Exchange step for a block of words: each goes to the class that raises the likelihood most.

    A word is taken out of its own class (``now``, -1: in none yet) before the classes are compared; ties leave it
    where it is.
    """
    held, total = step.held, step.total
    gain = step.sums(ctx, n, starts)
    counts, of = np.unique(c, return_inverse=True)
    gain -= (2 * (_xlogx(total + counts[:, None]) - step.total_before))[of]
    inside = np.flatnonzero(now >= 0)
    if len(inside):
        word = np.repeat(np.arange(len(c)), np.diff(starts, append=len(ctx)))
        own = held[now[word], ctx]
        kept = np.add.reduceat(step.before[ctx, now[word]] - _xlogx(own - n), starts) - 2 * (step.total_before[now] - _xlogx(total[now] - c))
        gain[inside, now[inside]] = kept[inside] + 1e-9
    gain[:, 0] = -np.inf  # the text boundary stays alone
    return gain.argmax(axis=1)


def assign(words: pa.Array, c: np.ndarray, size: np.ndarray, x: np.ndarray, steps: list[Step], names: pa.Array, seed_class: np.ndarray):
    """(class or -1 of each word, contexts and counts of their cells, class of each cell) after ``steps`` in order."""
    edge = np.concatenate([[0], np.cumsum(size)])
    ctx, n = x & ((1 << CELL) - 1), (x >> CELL).astype(float)
    now = np.append(seed_class, -1)[places(words, names)]
    for a in range(0, len(c), 1024):
        b = min(a + 1024, len(c))
        part, fixed = slice(edge[a], edge[b]), now[a:b] >= 0
        block = np.full(b - a, -1)
        for step in steps:
            block = moved(ctx[part], n[part], edge[a:b] - edge[a], c[a:b], block, step)
        now[a:b] = np.where(fixed, now[a:b], block)
    return now, ctx, n, np.repeat(now, size)


def likelihood(held: np.ndarray) -> float:
    """Log likelihood of the contexts given the classes, but for a constant."""
    return float(_xlogx(held).sum() - 2 * _xlogx(held[:, : held.shape[1] // 2].sum(axis=1)).sum())


class ClassModel:
    """Learned classes, counts and probabilities; ``score`` applies them to every document.

    ``learn``: condition on rows of ``docs`` to learn from (default: all).  ``least``: count from which a word is clustered.
    """

    def __init__(self, docs: DataFrame, learn: Column | None = None, classes: int = CLASSES, clustered: int = CLUSTERED, least: int = LEAST, head: int = HEAD, sweeps: int = SWEEPS):
        if not 2 <= classes <= 240:
            raise ValueError("classes must lie between 2 and 240")
        self.spark, self.classes, self.least = docs.sparkSession, classes, least
        learn = F.lit(True) if learn is None else F.coalesce(learn, F.lit(False))
        texts = docs.where(learn).select(F.col("text").cast("string").alias("text"))
        counts = stored(word_counts(texts), "word-counts")
        total = counts.agg(F.sum("c"), F.count(F.lit(1)), F.sum(F.when(F.length("word") == 0, F.col("c")))).first()
        self.n, self.v, self.ends = int(total[0] or 0), int(total[1]), int(total[2] or 0)
        top = [bytes(r.word) for r in counts.where((F.length("word") > 0) & (F.col("c") >= least)).orderBy(F.desc("c"), "word").limit(clustered - 1).collect()]  # seeds only
        ids = {b"": 0} | {w: k for k, w in enumerate(top, 1)}
        of = exchange_clusters(seed_pairs(texts, ids), classes)
        seeds = {w: int(of[k]) for w, k in ids.items()}
        self._spread(stored(contexts(texts, seeds, classes, least, self.n), "lm-contexts"), seeds, sweeps)
        self._emissions(head)
        self.coded = self.encode(docs, learn)
        self._transitions()

    def _spread(self, found: DataFrame, seeds: dict[bytes, int], sweeps: int) -> None:
        """Exchange of all words beyond the seeds.  A step is a function of a word's contexts and the small matrices of
        the steps before it, so each pass repeats the steps so far and nothing is stored between passes."""
        classes, width = self.classes, self.classes + FORMS
        often, rare = found.where("often"), found.where("not often")
        listed, seed_class = list(seeds), np.array(list(seeds.values()))

        def summed(history: list[np.ndarray]) -> np.ndarray:
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                steps, names = [Step(h) for h in history], pa.array(listed, pa.binary())
                held = np.zeros(classes * 2 * width)
                for row in unpacked(batches):
                    _, ctx, n, k = assign(*row, steps, names, seed_class)
                    fine = k >= 0
                    held += np.bincount(k[fine] * 2 * width + ctx[fine], weights=n[fine], minlength=len(held))
                at = np.flatnonzero(held)
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(held[at].astype(np.int64))], names=["cell", "n"])

            got = often.mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()  # at most classes * 2 * width rows
            out = np.zeros(classes * 2 * width)
            out[got.column("cell").to_numpy()] = got.column("n").to_numpy()
            return out.reshape(classes, 2 * width)

        history = [summed([])]
        self.gains: list[float] = []
        for step in range(sweeps):
            held = summed(history)
            self.gains.append(likelihood(held))
            if step + 1 == sweeps or step and self.gains[-1] <= self.gains[-2] * (1 - 1e-4 if self.gains[-2] < 0 else 1 + 1e-4):
                break
            history.append(held)
        if len(self.gains) > 1 and self.gains[-1] < self.gains[-2]:
            history.pop()  # the last step did not help

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            steps, names = [Step(h) for h in history], pa.array(listed, pa.binary())
            for row in unpacked(batches):
                yield formed(row[0], row[1], assign(*row, steps, names, seed_class)[0])

        def plain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for words, c, _, _ in unpacked(batches):
                yield formed(words, c, None)

        def formed(words: pa.Array, c: np.ndarray, k: np.ndarray | None) -> pa.RecordBatch:
            form = forms(words)
            return pa.RecordBatch.from_arrays([words, pa.array(c), pa.array(form + classes if k is None else k, pa.int32()), pa.array(form, pa.int32())], names=["word", "c", "k", "form"])

        shape = "word binary, c long, k int, form int"
        self.words = stored(often.mapInArrow(run, shape).unionByName(rare.mapInArrow(plain, shape)), "lm-classes")

    def _emissions(self, head: int) -> None:
        """Tokens of each class, discounts of the form classes, and the head words that are broadcast.

        Words of form classes are the rare ones.  Of the tokens that meet such a class later, the share of unknown
        words is estimated by n1 / (n1 + 2 n2), n1 and n2 the words of that form seen once and twice."""
        size = self.classes + FORMS
        self.class_tokens = np.zeros(size)
        self.class_tokens[0] = self.ends
        types = np.zeros(FORMS)
        for r in self.words.groupBy("k").agg(F.sum("c").alias("c"), F.count(F.lit(1)).alias("v")).collect():  # one row a class
            self.class_tokens[r.k] += r.c
            if r.k >= self.classes:
                types[r.k - self.classes] = r.v
        once = np.zeros((FORMS, 2))
        for r in self.words.groupBy("form").agg(F.count_if(F.col("c") == 1), F.count_if(F.col("c") == 2)).collect():  # FORMS rows
            once[r[0]] = r[1:]
        cut = np.where(once[:, 0] > 0, once[:, 0] / np.maximum(1, once[:, 0] + 2 * once[:, 1]), 0.5)
        self.discount = np.clip(cut, 0.05, 0.95)
        self.form_tokens = np.maximum(1, self.class_tokens[self.classes :])
        # log10 of the unknown word in each form class
        self.unknown = np.log10(np.where(types > 0, self.discount * types / self.form_tokens, 1.0))
        listed = most_frequent(self.words, head).select("word", "c", "k").toArrow()  # head rows
        c, k = listed.column("c").to_numpy().astype(float), listed.column("k").to_numpy()
        less = np.concatenate([np.zeros(self.classes), self.discount])
        self.head = {w: i for i, w in enumerate(listed.column("word").to_pylist())}
        self.head_facts = (np.log10(c + 1) - math.log10(self.n + self.v + 1), np.log10((c - less[k]) / self.class_tokens[k]), k.astype(np.uint8))

    def classify(self, word: bytes) -> int:
        """Class of a word: from the head, else from the table of all words, else by its form."""
        if word in self.head:
            return int(self.head_facts[2][self.head[word]])
        got = self.words.where(F.col("word") == F.lit(bytearray(word))).select("k").head()
        return self.classes + form_of(word) if got is None else got.k

    def encode(self, docs: DataFrame, learn: Column | None = None) -> DataFrame:
        """doc_id, learn, n_tokens, n_known, base_score, own (emissions), seq: a byte for the class of each token but the end."""
        shared = self.spark.sparkContext.broadcast((list(self.head), *self.head_facts))
        rare, ends, denominator = 255, self.ends, math.log10(self.n + self.v + 1)
        end = math.log10(ends + 1) - denominator

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            head, base, own, of = shared.value
            head = pa.array(head, pa.binary())
            row = TaskContext.get().partitionId() << 40
            for block in blocks(batches):
                at, edge, words = cut(block.column(2))
                at = at.astype(np.int64)
                found, form = places(words, head), forms(words)
                texts, met = len(edge) - 1, found[at]
                there = met >= 0
                text = np.repeat(np.arange(texts), np.diff(edge))
                seq = np.full(len(at), rare, np.uint8)
                seq[there] = of[met[there]]
                known = np.bincount(text[there], minlength=texts) + (ends > 0)
                base_score = np.bincount(text[there], weights=base[met[there]], minlength=texts) + end
                emitted = np.bincount(text[there], weights=own[met[there]], minlength=texts)
                rest = np.flatnonzero(~there)
                tails = pa.StructArray.from_arrays([words.take(pa.array(at[rest])), pa.array(form[at[rest]], pa.int32()), pa.array(rest - edge[text[rest]], pa.int32())], names=["word", "form", "place"])
                cols = [np.arange(row + 1, row + texts + 1), np.diff(edge) + 1, known, base_score, emitted]
                types = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
                row += texts
                lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(rest, edge), pa.int32()), tails)
                yield pa.RecordBatch.from_arrays([block.column(0), block.column(1), *(pa.array(c, t) for c, t in zip(cols, types, strict=True)), _packed(seq, edge), lists], names=["doc_id", "learn", "row", "n_tokens", "n_known", "base_score", "own", "seq", "rest"])

        shape = "doc_id long, learn boolean, row long, n_tokens long, n_known long, base_score double, own double, seq binary, rest array<struct<word:binary,form:int,place:int>>"
        rows = docs.select(F.col("doc_id").cast("long"), (F.lit(False) if learn is None else learn).alias("learn"), F.col("text").cast("string"))
        whole = stored(rows.mapInArrow(run, shape), "lm-heads")
        rest = whole.select("row", F.inline("rest"))
        met = rest.join(self.words.select("word", "c", "k"), "word", "left")
        c, form = F.coalesce("c", F.lit(0)), F.col("form") + 1
        less, of_form, unknown = (F.element_at(F.array(*map(F.lit, map(float, values))), form) for values in (self.discount, self.form_tokens, self.unknown))
        of_class = F.element_at(F.array(*map(F.lit, map(float, np.maximum(1, self.class_tokens)))), F.coalesce("k", F.lit(0)) + 1)
        own = F.when(c == 0, unknown).when(F.col("k") >= self.classes, F.log10((F.greatest(c, F.lit(1)) - less) / of_form)).otherwise(F.log10(c / of_class))
        met = met.select("row", "place", c.alias("c"), F.coalesce("k", self.classes + F.col("form")).cast("int").alias("k"), own.alias("o"), (F.log10(c + 1.0) - denominator).alias("b"))
        sums = met.groupBy("row").agg(F.sum("b").alias("b"), F.sum("o").alias("o"), F.count_if(F.col("c") > 0).alias("m"), F.collect_list(F.struct("place", "k")).alias("tail"))
        zero = F.lit(0.0)
        both = whole.join(sums, "row", "left").select("doc_id", "learn", "n_tokens", (F.col("n_known") + F.coalesce("m", F.lit(0))).alias("n_known"), (F.col("base_score") + F.coalesce("b", zero)).alias("base_score"), (F.col("own") + F.coalesce("o", zero)).alias("own"), "seq", F.coalesce("tail", F.array()).alias("tail"))

        def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                held, edge = _binary(batch.column(6))
                held, tails = held.copy(), batch.column(7)
                flat = tails.flatten()
                held[np.repeat(edge[:-1], np.diff(tails.offsets.to_numpy())) + flat.field(0).to_numpy()] = flat.field(1).to_numpy()
                yield pa.RecordBatch.from_arrays([*batch.columns[:6], _packed(held, edge)], names=batch.schema.names[:7])

        return stored(both.mapInArrow(fill, "doc_id long, learn boolean, n_tokens long, n_known long, base_score double, own double, seq binary"), "lm-sequences")

    def _transitions(self) -> None:
        size = self.classes + FORMS

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen = np.zeros(size * size, np.int64)
            for batch in batches:
                code, _ = _bounded(batch.column(0))
                seen += np.bincount(code[:-1] * size + code[1:], minlength=size * size)
            at = np.flatnonzero(seen)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(seen[at])], names=["pair", "n"])

        got = self.coded.where("learn").select("seq").mapInArrow(run, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).toArrow()  # at most size^2 rows
        pairs = np.zeros(size * size)
        pairs[got.column("pair").to_numpy()] = got.column("n").to_numpy()
        pairs = pairs.reshape(size, size)
        tokens_in = pairs.sum(axis=0)
        share = (tokens_in + 0.5) / (tokens_in.sum() + 0.5 * size)
        self.step = np.log10((pairs + PULL * share[None, :]) / (pairs.sum(axis=1, keepdims=True) + PULL))

    def score(self, docs: DataFrame | None = None) -> DataFrame:
        """doc_id, n_tokens, n_known, base_score, score of ``docs`` (default: the rows the model was made with)."""
        step = self.step

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                code, text = _bounded(batch.column(5))
                score = np.bincount(text, weights=step[code[:-1], code[1:]], minlength=batch.num_rows) + batch.column(4).to_numpy()
                yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(score, pa.float64())], names=["doc_id", "n_tokens", "n_known", "base_score", "score"])

        coded = self.coded if docs is None else self.encode(docs)
        rows = coded.select("doc_id", "n_tokens", "n_known", "base_score", "own", "seq")
        return rows.mapInArrow(run, "doc_id long, n_tokens long, n_known long, base_score double, score double")


def _bounded(seqs: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Classes of the tokens of all texts with a boundary (class 0) before, between and after them; text of each pair there."""
    data, edge = _binary(seqs)
    return np.insert(data, edge, 0).astype(np.int64), np.repeat(np.arange(len(seqs)), np.diff(edge) + 1)


def held_out() -> Column:
    return crc32_of_id() % 7 == 2


def op6_class_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = ClassModel(docs, ~F.coalesce(held_out(), F.lit(False)))
    out = model.score()
    return out.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "n_tokens", "n_known", F.lit(model.n).cast("long").alias("train_tokens"), "base_score", "score")
