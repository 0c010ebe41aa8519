"""Toxicity: a Levenshtein automaton intersected with a lexicon trie, and scores of the context window.

The lexicon is learnt from labelled rows: words and stems (beginnings that many words share) that stand far more often in distinct toxic texts
than in others, whatever their share of them: a language with few labelled rows has its terms, too. That a term is no chance find among all
words and stems is tested (CHANCE); in samples too small for the test, a least share of the toxic texts will do. A word that begins with a stem
is a hit of the stem, and has features of its own.
Its trie and the automaton for the allowed edits (one, two for long terms) are walked together, and their product is made
deterministic as words ask for it, so that a word costs one look-up a character and most end after a few. A word near a term is a hit;
near misses that are as frequent in clean labelled texts are not. Each hit is scored by its window, the words before and after it: inside
quotation marks of its line or near a word of reporting it is a quotation, near a second person or an intensifier it is abuse. A logistic regression
on these counts gives the score.

What is learnt comes from a bounded sample of labelled rows (SAMPLE_ROWS, by hash of the id; a classifier's fit); every text is
scored, whole. Without any labels, or without a toxic one, scores are the prior rate (0 without labels). Null and empty texts have no hits.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyloom.llm.common import released, written

SAMPLE_ROWS = 20_000
#: A term stands in so many distinct toxic texts at least, so many times as often in them as in clean ones, and either by a chance of CHANCE at most
#: (over all words and stems together) or in the share TERM_SHARE of the toxic texts.
TERM_SHARE, TERM_TEXTS, TERM_RATIO, MAX_TERMS, CHANCE = 0.1, 3, 20.0, 400, 0.01
#: Stems are counted, so that they may stand in more clean texts, by chance.
LEAST_LETTERS, LONG_LETTERS, LEAST_STEM, STEM_RATIO, STEM = 4, 9, 3, 5.0, "*"
WINDOW = 5
REMEMBERED = 300_000

#: Words of reporting, of the second person and of intensity.
REPORTING = frozenset("said says say wrote writes called calls quoted quote quotes word term insult slur dit écrit mot sagte schrieb wort nannte dijo escribió palabra llamó".split())
ADDRESSING = frozenset("you your yours youre u such what absolute total complete fucking damn du dein deine ihr tu ton ta vous votre tú tus usted".split())
QUOTED = re.compile("[\"“”„«»]")
LINE_END = re.compile("\n")
WORD = re.compile(r"\w+")


class FuzzyLexicon:
    """The deterministic product of a trie of terms and their Levenshtein automata, made as it is walked."""

    def __init__(self, terms: list[str]):
        self.terms = sorted(terms)
        self.children: list[dict[str, int]] = [{}]
        self.term_at: dict[int, str] = {}
        self.budget = [0]
        for term in self.terms:
            at, allowed = 0, self.edits(term)
            self.budget[0] = max(self.budget[0], allowed)
            for c in term:
                if c not in self.children[at]:
                    self.children[at][c] = len(self.children)
                    self.children.append({})
                    self.budget.append(0)
                at = self.children[at][c]
                self.budget[at] = max(self.budget[at], allowed)
            self.term_at[at] = term
        self.letters = {c for t in self.terms for c in t}
        self.states: list[tuple[tuple[int, int], ...]] = []
        self.number: dict[tuple[tuple[int, int], ...], int] = {}
        self.step: dict[tuple[int, str], int] = {}
        self.start = self._state({0: 0})
        self.accepts: dict[int, tuple[int, str] | None] = {}

    @staticmethod
    def edits(term: str) -> int:
        return 2 if len(term) >= LONG_LETTERS else 1 if len(term) >= LEAST_LETTERS else 0

    def _state(self, nodes: dict[int, int]) -> int:
        """The state of these (node, edits), after all letters that a word may leave out; -1 if none is left."""
        left = list(nodes.items())
        while left:
            node, cost = left.pop()
            for child in self.children[node].values():
                if cost + 1 <= self.budget[child] and cost + 1 < nodes.get(child, 99):
                    nodes[child] = cost + 1
                    left.append((child, cost + 1))
        key = tuple(sorted(nodes.items()))
        if not key:
            return -1
        if key not in self.number:
            self.number[key] = len(self.states)
            self.states.append(key)
        return self.number[key]

    def _next(self, state: int, c: str) -> int:
        nodes: dict[int, int] = {}

        def put(node: int, cost: int) -> None:
            if cost <= self.budget[node] and cost < nodes.get(node, 99):
                nodes[node] = cost

        for node, cost in self.states[state]:
            put(node, cost + 1)
            for letter, child in self.children[node].items():
                put(child, cost + (letter != c))
        return self._state(nodes)

    def _accept(self, state: int) -> tuple[int, str] | None:
        ends = [(cost, self.term_at[node]) for node, cost in self.states[state] if node in self.term_at and cost <= self.edits(self.term_at[node])]
        return min(ends, default=None)

    def find(self, word: str) -> tuple[int, str] | None:
        """(edits, term) of the nearest term within its edits; ties go to the first by spelling."""
        state, step, letters = self.start, self.step, self.letters
        for c in word:
            key = (state, c if c in letters else "")
            if (after := step.get(key)) is None:
                after = step[key] = self._next(*key)
            if after < 0:
                return None
            state = after
        if state not in self.accepts:
            self.accepts[state] = self._accept(state)
        return self.accepts[state]


@dataclass
class Model:
    terms: list[str]
    stems: frozenset[str] = frozenset()
    innocent: frozenset[str] = frozenset()
    weights: np.ndarray = field(default_factory=lambda: np.zeros(len(FEATURES)))
    bias: float = -30.0

    def score(self, features: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(features @ self.weights + self.bias, -30, 30)))


#: What a text's hits are counted as, and the weight that a count has as long as labels don't say otherwise: a misspelling counts like its
#: term, less a little; an abusive window adds to a hit; a quotation is counted apart.
FEATURES = {"unquoted hits": 0.0, "in an abusive window": 0.5, "quoted hits": 0.0, "misspelled": -1.5, "distinct terms": 0.0, "stems": 0.0, "share of stems": 0.0, "share of words": 0.0}


class _Known(dict):
    """Word -> what the lexicon finds; bounded."""

    def __init__(self, terms: list[str], innocent: frozenset[str], stems: frozenset[str] = frozenset()):
        super().__init__()
        self.lexicon, self.innocent, self.stems = FuzzyLexicon(terms), innocent, stems
        self.lengths = sorted({len(s) for s in stems})

    def __missing__(self, word: str) -> tuple[int, str] | None:
        found = None if word in self.innocent else self.lexicon.find(word)
        if found is None or found[0]:
            found = next(((0, word[:n] + STEM) for n in self.lengths if word[:n] in self.stems), found)
        if len(self) >= REMEMBERED:
            self.clear()
        self[word] = found
        return found


def _in_quotes(start: int, end: int, quotes: list[int], ends: list[int]) -> bool:
    """Whether an odd number of quotation marks stands before the place in its line, and one after it; both lists are sorted."""
    line = bisect_left(ends, start)
    first, last = ends[line - 1] if line else -1, ends[line] if line < len(ends) else math.inf
    before = bisect_left(quotes, start)
    after = bisect_left(quotes, end)
    return (before - bisect_left(quotes, first)) % 2 == 1 and after < len(quotes) and quotes[after] < last


def features(text: str | None, known: _Known) -> list[float]:
    """The counts of FEATURES, all but shares as logarithms; those of stems apart from those of terms."""
    out = [0.0] * len(FEATURES)
    low = (text or "").lower()
    words = WORD.findall(low)
    hits = [(i, found) for i, found in enumerate(map(known.__getitem__, words)) if found is not None]
    if not hits:
        return out
    at = [(m.start(), m.end()) for m in WORD.finditer(low)]
    quotes, ends = [m.start() for m in QUOTED.finditer(low)], [m.start() for m in LINE_END.finditer(low)]
    terms = set()
    for i, (edits, term) in hits:
        near = words[max(0, i - WINDOW) : i] + words[i + 1 : i + 1 + WINDOW]
        if _in_quotes(*at[i], quotes, ends) or not REPORTING.isdisjoint(near):
            out[2] += not term.endswith(STEM)
            continue
        if term.endswith(STEM):
            out[5] += 1
            continue
        out[0] += 1
        out[1] += not ADDRESSING.isdisjoint(near)
        out[3] += edits > 0
        terms.add(term)
    out[4] = len(terms)
    # shares of stems are of a per cent, where clean texts have theirs by chance
    return [float(np.log1p(x)) for x in out[:6]] + [float(np.log1p(100 * out[5] / len(words))), out[0] / len(words)]


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def labelled_sample(docs: DataFrame, labels: DataFrame, allowed: Column, rows: int = SAMPLE_ROWS) -> DataFrame:
    """(text, toxic) of at most ``rows`` labelled documents, chosen by a hash of the id. ``allowed``: a condition on doc_id."""
    chosen = labels.where("doc_id is not null and toxic is not null").where(allowed).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows).withColumnRenamed("doc_id", "l_id")
    return docs.join(F.broadcast(chosen), F.col("doc_id") == F.col("l_id")).select("text", "toxic")  # at most ``rows`` ids


def learn(docs: DataFrame, labels: DataFrame, allowed: Column, id_col: str = "doc_id", text_col: str = "text", rows: int = SAMPLE_ROWS) -> Model:
    """The lexicon, its innocent neighbours and the weights, from labelled rows that satisfy ``allowed``."""
    sample = labelled_sample(_texts(docs, id_col, text_col), labels, allowed, rows).where("text is not null")
    distinct = sample.groupBy(F.md5(F.col("text").cast("binary")).alias("h")).agg(F.max("toxic").alias("toxic"), F.first("text").alias("text"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, list[int]] = defaultdict(lambda: [0, 0])
        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                total[""][toxic > 0] += 1
                words = set(WORD.findall(text.lower()))
                for w in words | {w[:n] + STEM for w in words for n in range(LEAST_STEM, len(w))}:
                    total[w][toxic > 0] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(total)), pa.array([v[0] for v in total.values()], pa.int64()), pa.array([v[1] for v in total.values()], pa.int64())], names=["w", "clean", "toxic"])

    counts = distinct.select("text", "toxic").mapInArrow(released(count), "w string, clean long, toxic long").groupBy("w").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    counts, _ = written(counts, "words")
    total = counts.where("w = ''").first()
    n_clean, n_toxic = (total["clean"], total["toxic"]) if total else (0, 0)
    if not n_toxic:
        return Model([])
    ratio = ((F.col("toxic") + 0.5) / (n_toxic + 1)) / ((F.col("clean") + 0.5) / (n_clean + 1))
    # A bound of the chance that of so many texts with it so many are toxic: exp(-gain).
    prior, either = n_toxic / (n_toxic + n_clean), F.col("toxic") + F.col("clean")
    gain = F.col("toxic") * F.log(F.col("toxic") / either / prior) + F.when(F.col("clean") > 0, F.col("clean") * F.log(F.col("clean") / either / max(1 - prior, 1e-9))).otherwise(0.0)
    known = (gain >= float(np.log(counts.count() / CHANCE))) | (F.col("toxic") >= TERM_SHARE * n_toxic)
    stem = F.col("w").endswith(STEM)
    wanted = (F.col("toxic") >= TERM_TEXTS) & (ratio >= F.when(stem, STEM_RATIO).otherwise(TERM_RATIO)) & (F.length("w") >= F.when(stem, LEAST_STEM + 1).otherwise(LEAST_LETTERS)) & known
    found = counts.where("w <> ''").where(wanted).select("w", "toxic", ratio.alias("ratio"), gain.alias("gain")).collect()
    stems = _stems(found)
    of_stem = lambda w: any(w[:n] in stems for n in range(LEAST_STEM, len(w) + 1))
    terms = sorted((r for r in found if not r["w"].endswith(STEM) and not of_stem(r["w"])), key=lambda r: (-r["ratio"], r["w"]))
    terms = [r["w"] for r in terms[:MAX_TERMS]]

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = FuzzyLexicon(terms)
        for batch in batches:
            yield batch.filter(pa.array([(f := lexicon.find(w)) is not None and f[0] > 0 for w in batch.column(0).to_pylist()], pa.bool_()))

    kind = counts.schema
    plain = counts.where(~stem & (ratio < 3)).mapInArrow(released(near), kind) if terms else counts.limit(0)
    innocent = frozenset(r["w"] for r in plain.select("w").collect())  # words within the edits of MAX_TERMS terms, in SAMPLE_ROWS texts

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Known(terms, innocent, stems)
        for batch in batches:
            x = np.array([features(t, known) for t in batch.column(0).to_pylist()], float).reshape(-1, len(FEATURES))
            yield pa.RecordBatch.from_arrays([*(pa.array(c) for c in x.T), batch.column(1)], names=[*names, "toxic"])

    names = [f"f{i}" for i in range(len(FEATURES))]
    grid = sample.mapInArrow(released(measure), ", ".join(f"{n} double" for n in names) + ", toxic int").groupBy(*names, "toxic").count().toPandas()
    weights, bias = _logistic(grid[names].to_numpy(), grid["toxic"].to_numpy(float), grid["count"].to_numpy(float))
    return Model(terms, stems, innocent, weights, bias)


def _stems(found: list) -> frozenset[str]:
    """Of nested beginnings the one of the greatest gain; none that is but one word and its variants."""
    words = [(r["w"], r["toxic"]) for r in found if not r["w"].endswith(STEM)]
    most: dict[str, int] = defaultdict(int)
    for w, n in words:
        for k in range(LEAST_STEM, len(w) + 1):
            most[w[:k]] = max(most[w[:k]], n)
    taken: set[str] = set()
    begun: set[str] = set()
    for r in sorted((r for r in found if r["w"].endswith(STEM)), key=lambda r: (-r["gain"], len(r["w"]), r["w"])):
        s = r["w"][: -len(STEM)]
        if 2 * most[s] > r["toxic"] or s in begun or any(s[:k] in taken for k in range(LEAST_STEM, len(s))):
            continue
        taken.add(s)
        begun |= {s[:k] for k in range(LEAST_STEM, len(s))}
    return frozenset(taken)


def _logistic(x: np.ndarray, y: np.ndarray, n: np.ndarray, ridge: float = 1.0) -> tuple[np.ndarray, float]:
    """Weighted logistic regression by Newton steps, with a ridge around the weights of FEATURES."""
    order = np.lexsort((*x.T, y))
    a = np.column_stack((x, np.ones(len(x))))[order]
    y, n, prior = y[order], n[order], np.array([*FEATURES.values(), 0.0])
    w = prior.copy()
    penalty = np.diag([ridge] * x.shape[1] + [1e-6])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (n * p * (1 - p))[:, None]).T @ a + penalty, a.T @ (n * (y - p)) - penalty @ (w - prior))
        w += step * min(1.0, 4 / max(np.abs(step).max(), 1e-9))
        if np.abs(step).max() < 1e-8:
            break
    return w[:-1], float(w[-1])


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score double), one row per document."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        known = _Known(model.terms, model.innocent, model.stems)
        for batch in batches:
            x = np.array([features(t.as_py(), known) for t in batch.column(1)], float).reshape(-1, len(FEATURES))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(x))], names=["doc_id", "score"])

    rows = _texts(docs, id_col, text_col)
    return rows.mapInArrow(released(run), f"doc_id {rows.schema[0].dataType.simpleString()}, score double")


def reject(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is below the threshold."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        known = _Known(model.terms, model.innocent, model.stems)
        for batch in batches:
            x = np.array([features(t.as_py(), known) for t in batch.column(place)], float).reshape(-1, len(FEATURES))
            yield batch.filter(pa.array(model.score(x) < threshold))

    return docs.mapInArrow(released(run), docs.schema)


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of query op8: doc_id, held_out, score, predicted."""
    model = learn(docs, labels, ~held_out())
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
