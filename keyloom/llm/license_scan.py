"""Licence scan by a positional index of rare words.

Licence templates (full texts, notices, phrases) are word sequences with mandatory key phrases. By inverse document frequency over all documents each key phrase has
its RARE rarest words, and each template its rarest ones: the index maps such a word to its postings (phrase, place in it) and (template, place in it).
A text is looked up by the licence words it has, from the rarest on. The postings of a phrase's words are intersected by relative position:
a phrase can only begin where all of its rare words say so, and there it is verified word by word. As every place of a phrase has all of them, none is missed.
A template is found where all of its key phrases stand in their order, each at its distance from the one before, up to a slack of words and a part of the distance.

How much of a template stands there is told by its rare words: of those near their relative position the share, by inverse document frequency. The
score of a finding is that share, times how telling the words found are (their frequencies' sum against WEIGHT, so that three common words say less than a licence's whole text);
a document's score joins its templates as independent signs.

Words are maximal runs of digits, letters a-z (A-Z in lower case) and non-ASCII characters. Null and empty texts have no words.
Texts are taken whole; work is linear in their words and in the places of rare words.
"""

from __future__ import annotations

import math
from bisect import bisect_left, bisect_right
from collections import defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.llm.common import released
from keyloom.llm.license_texts import TEMPLATES, Template

#: Words by which a key phrase may be off its distance from the one before, and the part of the distance that is added.
SLACK, STRETCH = 8, 0.25
#: Rare words of a phrase, and of a template.
RARE, RARE_OF_TEMPLATE = 3, 24
#: The sum of inverse document frequencies at which words are half a proof.
WEIGHT = 12.0

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()


class Index:
    """The positional index of some templates, given how many of ``n_docs`` documents have each word."""

    def __init__(self, templates: tuple[Template, ...], frequency: dict[bytes, int], n_docs: int, slack: int = SLACK):
        self.templates, self.slack = templates, slack
        self.words = [words_of(t.text) for t in templates]
        self.idf = {w: math.log((n_docs + 1) / (frequency.get(w, 0) + 1)) + 1 for ws in self.words for w in ws}
        self.of_phrase: list[list[int]] = []
        self.phrases: list[list[bytes]] = []
        self.places: list[list[int]] = []
        number: dict[tuple[bytes, ...], int] = {}
        for t, template in enumerate(templates):
            own = [words_of(p) for p in template.phrases] or [self.words[t]]
            self.of_phrase.append([number.setdefault(tuple(p), len(number)) for p in own])
            self.places.append(_places(self.words[t], own))
        self.phrases = [list(p) for p in number]
        self.keys = [sorted(sorted(range(len(p)), key=lambda i: (-self.idf[p[i]], i))[:RARE]) for p in self.phrases]
        self.rare = [sorted(sorted(range(len(ws)), key=lambda i: (-self.idf[ws[i]], i * 0.6180339887 % 1))[:RARE_OF_TEMPLATE]) for ws in self.words]  # ties lie all over the template
        self.postings: dict[bytes, list[tuple[int, int]]] = defaultdict(list)
        for p, keys in enumerate(self.keys):
            for i in keys:
                self.postings[self.phrases[p][i]].append((p, i))
        self.looked_up = set(self.postings) | {self.words[t][i] for t, places in enumerate(self.rare) for i in places}

    def find(self, words: list[bytes]) -> list[tuple[int, int, float]]:
        """(template, first word, score) of every place where a template is found."""
        if self.postings.keys().isdisjoint(words):
            return []
        at: dict[bytes, list[int]] = defaultdict(list)
        for i, word in enumerate(words):
            if word in self.looked_up:
                at[word].append(i)
        starts = self._phrase_starts(words, at)
        found = []
        for t, phrases in enumerate(self.of_phrase):
            for begin in starts.get(phrases[0], ()):
                here, whole = begin, True
                for k in range(1, len(phrases)):
                    distance = self.places[t][k] - self.places[t][k - 1]
                    here = _nearest(starts.get(phrases[k], []), here + distance, self.slack + STRETCH * distance)
                    if here is None:
                        whole = False
                        break
                if whole:
                    found.append((t, begin, self._score(t, at, begin - self.places[t][0])))
        return found

    def _phrase_starts(self, words: list[bytes], at: dict[bytes, list[int]]) -> dict[int, list[int]]:
        """Where each phrase begins: postings are intersected from the text's rarest word on."""
        agreed: dict[int, set[int]] = {}
        for word in sorted(at.keys() & self.postings.keys(), key=lambda w: (-self.idf[w], w)):
            for p, offset in self.postings[word]:
                begins = {i - offset for i in at[word]}
                agreed[p] = begins if p not in agreed else agreed[p] & begins
        starts = {}
        for p, begins in agreed.items():
            phrase = self.phrases[p]
            held = sorted(b for b in begins if b >= 0 and words[b : b + len(phrase)] == phrase)
            if held:
                starts[p] = held
        return starts

    def _score(self, t: int, at: dict[bytes, list[int]], origin: int) -> float:
        """The share of the template's rare words near their places, by inverse document frequency, times how telling those found are."""
        there = total = 0.0
        for place in self.rare[t]:
            word = self.words[t][place]
            weight = self.idf[word]
            total += weight
            there += weight * (_nearest(at.get(word, []), origin + place, self.slack + STRETCH * place) is not None)
        return there / total * there / (there + WEIGHT)


def _places(words: list[bytes], phrases: list[list[bytes]]) -> list[int]:
    """Where each phrase stands in the template's words, after the one before."""
    places, low = [], 0
    for phrase in phrases:
        low = next(i for i in range(low, len(words)) if words[i : i + len(phrase)] == phrase)
        places.append(low)
        low += len(phrase)
    return places


def _nearest(places: list[int], wanted: float, off: float) -> int | None:
    """The place nearest to the wanted one, if it isn't further off than that; of sorted places."""
    low, high = bisect_left(places, wanted - off), bisect_right(places, wanted + off)
    return min(places[low:high], key=lambda x: abs(x - wanted)) if low < high else None


def document_frequency(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, text_col: str = "text") -> tuple[dict[bytes, int], int]:
    """How many documents have each word of the templates, and how many documents there are: one pass; the driver gets a row for each template word."""
    vocabulary = {w for t in templates for w in words_of(t.text)}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[bytes, int] = defaultdict(int)
        for batch in batches:
            total[b""] += batch.num_rows
            for text in batch.column(0):
                for w in vocabulary.intersection(words_of(text.as_py())):
                    total[w] += 1
        yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in total], pa.string()), pa.array(list(total.values()), pa.int64())], names=["w", "n"])

    rows = docs.select(F.col(text_col).cast("string")).mapInArrow(released(count), "w string, n long").groupBy("w").agg(F.sum("n").alias("n")).collect()
    found = {r["w"].encode(): r["n"] for r in rows}
    return found, found.pop(b"", 0)


def scan(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, id_col: str = "doc_id", text_col: str = "text", slack: int = SLACK) -> DataFrame:
    """(doc_id, n_words, found array<(template, label, base, first_word, score)>), one row per document; places in order."""
    index = Index(templates, *document_frequency(docs, templates, text_col), slack)
    kind = pa.list_(pa.struct([("template", pa.int32()), ("label", pa.string()), ("base", pa.bool_()), ("first_word", pa.int64()), ("score", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts, found = [], []
            for text in batch.column(1):
                words = words_of(text.as_py())
                counts.append(len(words))
                hits = sorted(index.find(words), key=lambda h: (h[1], h[0]))
                found.append([{"template": t, "label": templates[t].label, "base": templates[t].base, "first_word": at, "score": score} for t, at, score in hits])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(found, kind)], names=["doc_id", "n_words", "found"])

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(released(run), f"doc_id {rows.schema[0].dataType.simpleString()}, n_words long, found array<struct<template: int, label: string, base: boolean, first_word: long, score: double>>")


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op1; score joins the best finding of each template."""
    base = F.filter("found", lambda x: x["base"])
    joined = lambda found: F.array_join(F.array_sort(F.array_distinct(F.transform(found, lambda x: x["label"]))), ",")
    starts = F.transform(base, lambda x: x["first_word"])
    best = F.map_from_entries(F.transform(F.array_sort(F.array_distinct(F.transform("found", lambda x: x["template"]))), lambda t: F.struct(t, F.array_max(F.transform(F.filter("found", lambda x: x["template"] == t), lambda x: x["score"])))))
    score = 1.0 - F.aggregate(F.map_values(best), F.lit(1.0), lambda left, x: left * (1.0 - x))
    return scan(docs).select("doc_id", "n_words", F.size(base).cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"), joined(base).alias("base_labels"), joined(F.col("found")).alias("labels"), score.alias("score"))
