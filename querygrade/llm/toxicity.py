"""Toxicity scores from a lexicon trie met by Levenshtein automata, with context windows.

The lexicon is learned from labelled training rows: whole words and word stems (prefixes) whose document
frequency in toxic rows is far above that in clean rows.  All terms form one trie.  A Levenshtein automaton
is intersected with it: a state is the set of trie nodes that a word's letters can have reached with the
edits spent so far; states are made once and shared by all words.  Whole words allow edits by their
length, stems none.

Every hit is judged in a window of words around it: quotation marks that open before and close after it, or
reporting cues, speak for quotation; second-person words for abuse.  A ridge logistic model over these
counts gives the score; its prior weights hold where the labels say nothing (for example no quoted hits).

Bounds: at most ``max_rows`` labelled rows are learned from (the ones with least hash of their id), and
``max_terms`` terms are kept; scores use neither label, language, source nor id.  Scoring is one map over
whole texts without a shuffle.

Defined cases: null or empty texts have no hits and get the base score; unlabelled or unusable labels (null,
not 0 or 1) are not learned from; repeated label rows count once, the larger label holds; without any toxic
training row all scores are 0; repeated document rows are scored each; an empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BoundedCache, crc32_of_id, table

MAX_ROWS = 20_000
MAX_TERMS = 4_000
CUT = 0.3
WINDOW = 8
STEM_LENGTHS = (3, 4, 5, 6, 7, 8)
EDGE = ".,;:!?\"'()[]{}<>«»“”„‘’*&%$#@|-_…~^`=+/\\"
QUOTES = "\"«»“”„"
# fixed values: words that report speech, and words that address someone
CUES = frozenset("said says wrote writes quote quoted quoting called calls reported alleged".split())
AIMED = frozenset("you your youre you're tu te toi vous du dich dir ihr tú usted ustedes".split())
FEATURES = ("plain", "near", "quoted", "kinds", "share", "aimed")
#: Prior weights of the logistic model on the features above, and its intercept.
PRIOR = np.array([1.2, 0.5, 0.2, 1.0, 0.3, 0.2])
PRIOR_BASE = -3.0


def bare(word: str) -> str:
    return word.strip(EDGE)


class LexiconAutomaton:
    """Least edits from a word to a lexicon term, by one deterministic automaton built on demand."""

    def __init__(self, words: dict[str, float], stems: dict[str, float], exact_only: frozenset[str] = frozenset()):
        self.next: list[dict[str, int]] = [{}]
        self.word_weight: dict[int, tuple[float, int, str]] = {}
        self.stem_weight: dict[int, float] = {}
        self.budget = [0]
        for term, weight in words.items():
            edits = 0 if len(term) < 5 or term in exact_only else 1 if len(term) < 9 else 2
            self.word_weight[self._insert(term, edits)] = (weight, edits, term)
        for term, weight in stems.items():
            self.stem_weight[self._insert(term, 0)] = weight
        self.states: list[dict[int, int]] = []
        self.ids: dict[frozenset, int] = {}
        self.moves: dict[tuple[int, str], int] = {}
        self.start = self._state({0: 0})

    def _insert(self, term: str, edits: int) -> int:
        node = 0
        self.budget[0] = max(self.budget[0], edits)
        for ch in term:
            if ch not in self.next[node]:
                self.next[node][ch] = len(self.next)
                self.next.append({})
                self.budget.append(0)
            node = self.next[node][ch]
            self.budget[node] = max(self.budget[node], edits)
        return node

    def _state(self, reach: dict[int, int]) -> int:
        todo = list(reach)
        while todo:  # letters of the lexicon that the word leaves out
            node = todo.pop()
            for child in self.next[node].values():
                cost = reach[node] + 1
                if cost <= self.budget[child] and cost < reach.get(child, 99):
                    reach[child] = cost
                    todo.append(child)
        if not reach:
            return -1
        key = frozenset(reach.items())
        if key not in self.ids:
            self.ids[key] = len(self.states)
            self.states.append(reach)
        return self.ids[key]

    def _move(self, state: int, ch: str) -> int:
        reach: dict[int, int] = {}

        def put(node: int, cost: int) -> None:
            if cost <= self.budget[node] and cost < reach.get(node, 99):
                reach[node] = cost

        for node, cost in self.states[state].items():
            put(node, cost + 1)
            for letter, child in self.next[node].items():
                put(child, cost + (letter != ch))
        return self._state(reach)

    def match(self, word: str) -> tuple[float, int, str] | None:
        """(weight, edits, term) of the nearest term, None if no term is near enough."""
        state, best = self.start, None
        for ch in word:
            key = (state, ch)
            if key not in self.moves:
                if len(self.moves) > 2_000_000:
                    self.moves.clear()
                self.moves[key] = self._move(state, ch)
            state = self.moves[key]
            if state < 0:
                return best
            if best is None and self.stem_weight:
                for node, cost in self.states[state].items():
                    if cost == 0 and node in self.stem_weight:
                        best = (self.stem_weight[node], 0, "")
        for node, cost in self.states[state].items():
            if node in self.word_weight:
                weight, allowed, term = self.word_weight[node]
                if cost <= allowed and (best is None or (cost, -weight) < (best[1], -best[0])):
                    best = (weight, cost, term)
        return best


class Scanner:
    """Features of a text from its hits and their windows."""

    def __init__(self, words: dict[str, float], stems: dict[str, float], exact_only: frozenset[str] = frozenset(), innocent: frozenset[str] = frozenset()):
        self.automaton = LexiconAutomaton(words, stems, exact_only)
        self.innocent = innocent
        self.cache = BoundedCache(self._look, 300_000)

    def _look(self, token: str) -> tuple[float, int, str] | None:
        word = bare(token)
        got = self.automaton.match(word) if word else None
        return None if got is not None and got[1] and word in self.innocent else got

    def features(self, text: str | None) -> list[float]:
        tokens = text.lower().split() if text else []
        look = self.cache.__getitem__
        hits = [(k, got) for k, got in enumerate(map(look, tokens)) if got is not None]
        plain = near = quoted = aimed = 0.0
        kinds = set()
        for k, (_, edits, _) in hits:
            before, after = tokens[max(0, k - WINDOW) : k], tokens[k + 1 : k + 1 + WINDOW]
            kinds.add(bare(tokens[k])[:5])
            marks_before = sum(t.count(q) for t in before for q in QUOTES) + sum(tokens[k][:1].count(q) for q in QUOTES)
            marks_after = sum(t.count(q) for t in after for q in QUOTES) + sum(tokens[k][-1:].count(q) for q in QUOTES)
            if (marks_before % 2 and marks_after) or any(bare(t) in CUES for t in before[-3:]):
                quoted += 1
            elif edits:
                near += 1
            else:
                plain += 1
            aimed += any(bare(t) in AIMED for t in before + after)
        return [np.log1p(plain), np.log1p(near), np.log1p(quoted), np.log1p(len(kinds)), 100.0 * (plain + near) / max(50, len(tokens)), np.log1p(aimed)]


def training_rows(docs: DataFrame, labels: DataFrame, train, max_rows: int = MAX_ROWS) -> DataFrame:
    """text, toxic: the bounded sample of labelled training rows (least hash of the id first)."""
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("doc_id is not null and toxic in (0, 1)").where(train)
    once = usable.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    sample = once.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)  # max_rows ids: safe to broadcast
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id").select("text", "toxic")


def _term_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: dict[int, Counter] = {0: Counter(), 1: Counter()}

    def flush():
        for toxic, held in counts.items():
            terms = list(held)
            for a in range(0, len(terms), 50_000):
                part = terms[a : a + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(np.full(len(part), toxic, np.int32)), pa.array([held[t] for t in part], pa.int64())], names=["term", "toxic", "n"])
            held.clear()

    for batch in batches:
        for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            words = {bare(w) for w in (text or "").lower().split()}
            terms = {w + "$" for w in words if 3 <= len(w) <= 30}
            for n in STEM_LENGTHS:
                terms.update(w[:n] for w in words if len(w) > n)
            counts[toxic].update(terms)
            counts[toxic][""] += 1
        if sum(map(len, counts.values())) > 400_000:
            yield from flush()
    yield from flush()


def learn_lexicon(rows: DataFrame, max_terms: int = MAX_TERMS) -> tuple[dict[str, float], dict[str, float]]:
    """(whole words, stems) with log-odds as weights; the term '' counts rows."""
    counted = rows.mapInArrow(_term_counts, "term string, toxic int, n long").groupBy("term").agg(F.sum(F.when(F.col("toxic") == 1, F.col("n")).otherwise(0)).alias("t"), F.sum(F.when(F.col("toxic") == 0, F.col("n")).otherwise(0)).alias("c"))
    total = counted.where("term = ''").first()
    if total is None or not total["t"]:
        return {}, {}
    t_all, c_all = total["t"], max(1, total["c"])
    odds = F.log((F.col("t") + 0.5) / (t_all + 1.0)) - F.log((F.col("c") + 0.5) / (c_all + 1.0))
    good = counted.where(F.col("term") != "").withColumn("odds", odds).where((F.col("t") >= 3) & (F.col("t") >= 0.01 * t_all) & (F.col("odds") >= 3.0) & (F.col("c") <= 0.03 * F.col("t") * c_all / t_all))
    words, stems = {}, {}
    for r in good.orderBy(F.desc("t"), F.desc("odds"), "term").limit(max_terms).collect():
        if r["term"].endswith("$"):
            words[r["term"][:-1]] = r["odds"]
        else:
            stems[r["term"]] = r["odds"]
    # a stem that stands for one whole word only says less than the word itself
    stems = {s: w for s, w in stems.items() if sum(x.startswith(s) for x in words) != 1 or s in words}
    return words, stems


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 2.0) -> tuple[float, np.ndarray]:
    """Ridge logistic regression around the prior weights; weights stay at 0 or above."""
    base, weights = PRIOR_BASE, PRIOR.copy()
    for _ in range(60):
        p = 1 / (1 + np.exp(-(base + x @ weights)))
        g = np.concatenate([[np.sum(p - y)], x.T @ (p - y) + ridge * (weights - PRIOR)])
        z = np.concatenate([np.ones((len(x), 1)), x], axis=1)
        h = (z * (p * (1 - p))[:, None]).T @ z + np.diag([1e-3] + [ridge] * len(weights))
        step = np.linalg.solve(h, g)
        step *= min(1.0, 2.0 / max(1e-9, np.abs(step).max()))
        base, weights = base - step[0], np.maximum(0.0, weights - step[1:])
        if np.abs(step).max() < 1e-6:
            break
    return float(base), weights


def learn_exceptions(rows: DataFrame, words: dict[str, float], stems: dict[str, float], most: int = 3) -> tuple[frozenset[str], frozenset[str]]:
    """(terms to match without edits, innocent forms): what edits of terms meet in clean training rows.

    A term whose edits meet more than ``most`` forms of clean rows is matched exactly; the few forms near
    other terms are exceptions.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner, found = Scanner(words, stems), set()
        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for token in set((text or "").lower().split()) if not toxic else ():
                    got = scanner.cache[token]
                    if got is not None and got[1]:
                        found.add((got[2], bare(token)))
        yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.string()) for k in (0, 1)], names=["term", "form"])

    forms = rows.mapInArrow(run, "term string, form string").distinct()
    per_term = forms.groupBy("term").agg(F.count("*").alias("n"), F.slice(F.array_sort(F.collect_set("form")), 1, most).alias("forms")).collect()  # max_terms rows
    return frozenset(r["term"] for r in per_term if r["n"] > most), frozenset(x for r in per_term if r["n"] <= most for x in r["forms"])


class ToxicityModel:
    """A learned lexicon with its exceptions and the logistic weights."""

    def __init__(self, lexicon: tuple, base: float, weights: np.ndarray):
        self.lexicon, self.base, self.weights = lexicon, base, weights

    def _scorer(self):
        lexicon, base, weights = self.lexicon, self.base, self.weights
        scanner = Scanner(*lexicon)

        def scores(texts: list) -> np.ndarray:
            if not lexicon[0] and not lexicon[1]:
                return np.zeros(len(texts))
            x = np.array([scanner.features(t) for t in texts]).reshape(-1, len(FEATURES))
            return 1 / (1 + np.exp(-(base + x @ weights)))

        return scores

    def score(self, docs: DataFrame) -> DataFrame:
        """doc_id, score."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            scores = self._scorer()
            for batch in batches:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores(batch.column(1).to_pylist()))], names=["doc_id", "score"])

        return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double")

    def keep_clean(self, docs: DataFrame, cut: float = CUT) -> DataFrame:
        """The rows of ``docs`` whose score is under ``cut``, all columns as they are; no shuffle."""
        at = docs.columns.index("text")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            scores = self._scorer()
            for batch in batches:
                yield batch.filter(pa.array(scores(batch.column(at).to_pylist()) < cut))

        return docs.mapInArrow(run, docs.schema)


def learn(docs: DataFrame, labels: DataFrame, train: Column | None = None, max_rows: int = MAX_ROWS, max_terms: int = MAX_TERMS) -> ToxicityModel:
    """Lexicon, exceptions and weights from the labelled rows that ``train`` (a condition on doc_id) admits."""
    rows = training_rows(docs, labels, F.lit(True) if train is None else train, max_rows)
    words, stems = learn_lexicon(rows, max_terms)
    if not words and not stems:
        return ToxicityModel(({}, {}), 0.0, PRIOR)
    lexicon = (words, stems, *learn_exceptions(rows, words, stems))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(*lexicon)
        for batch in batches:
            x = [scanner.features(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(x, pa.list_(pa.float64()))], names=["toxic", "x"])

    got = rows.mapInArrow(run, "toxic int, x array<double>").collect()  # max_rows rows of six numbers
    return ToxicityModel(lexicon, *fit_logistic(np.array([r["x"] for r in got]), np.array([r["toxic"] for r in got], float)))


def in_training() -> Column:
    return crc32_of_id() % 4 != 2


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = learn(docs, table(spark, sf_dir, "labels"), in_training())
    return model.score(docs).select("doc_id", (crc32_of_id() % 4 == 2).alias("held_out"), "score", F.when(F.col("score") >= CUT, 1).otherwise(0).alias("predicted"))
