"""Language identification by rank-order profiles and their out-of-place distance.

A text's letters, in lower case, with one boundary for each run of other characters, give n-grams of one to three characters.
A profile is the PROFILE most frequent n-grams in order of frequency. A text's own profile is compared with each language's: an n-gram
costs by how many places it is out of place, or PROFILE if the language's profile lacks it. The least sum wins; ties go
to the first language by code point.

Language profiles come from all rows that may be learnt from. Tasks add up counts of n-grams in sorted arrays and give one row for each
language and n-gram; the driver gets PROFILE rows for each language. Texts are taken whole. A text that is null or has no letter is ``und``
with score 0; so is every text if there was nothing to learn from.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from keyloom.llm.common import released

PROFILE = 400
UNKNOWN = "und"
#: A code point takes so many bits of an n-gram's number; no letter is 1, which stands for a boundary.
_BITS, _BOUNDARY = 21, 1
#: Numbers that a task gathers before it adds them up.
_GATHERED = 1 << 20


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def ngrams(text: str) -> np.ndarray:
    """The numbers of all n-grams of a text, repeats included; empty if it has no letter."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    letter = _letters()[codes]
    if not letter.any():
        return np.empty(0, np.int64)
    codes = np.concatenate(([_BOUNDARY], np.where(letter, codes, _BOUNDARY), [_BOUNDARY]))
    codes = codes[np.concatenate(([True], (codes[1:] != _BOUNDARY) | (codes[:-1] != _BOUNDARY)))]
    two = codes[:-1] << _BITS | codes[1:]
    return np.concatenate((codes[codes != _BOUNDARY], two, two[:-1] << _BITS | codes[2:]))


def profile(text: str, size: int = PROFILE) -> np.ndarray:
    """The most frequent n-grams in order; ties by number."""
    found, counts = np.unique(ngrams(text), return_counts=True)
    return found[np.argsort(-counts, kind="stable")[:size]]


class Profiles:
    """The profiles of all languages as one table of places."""

    def __init__(self, by_language: dict[str, list[int]], size: int = PROFILE):
        self.languages = sorted(by_language)
        self.size = size
        self.known = np.unique(np.array([g for gs in by_language.values() for g in gs], np.int64))
        self.places = np.full((len(self.known) + 1, len(self.languages)), -1, np.int64)
        for j, language in enumerate(self.languages):
            self.places[np.searchsorted(self.known, np.array(by_language[language], np.int64)), j] = np.arange(len(by_language[language]))

    def distances(self, own: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.known, own)
        at[(at >= len(self.known)) | (self.known[np.minimum(at, len(self.known) - 1)] != own)] = len(self.known)
        places = self.places[at]
        return np.where(places < 0, self.size, np.abs(places - np.arange(len(own))[:, None])).sum(axis=0)

    def predict(self, text: str | None) -> tuple[str, float]:
        """The language, and its part of all languages' nearness."""
        own = profile(text, self.size) if text and self.languages else ()
        if not len(own):
            return UNKNOWN, 0.0
        far = self.distances(own)
        near = 1 - far / (self.size * len(own))
        best = int(far.argmin())
        return self.languages[best], float(near[best] / near.sum()) if near.sum() > 0 else 0.0


class _Totals:
    """Counts of numbers in sorted arrays."""

    def __init__(self):
        self.waiting: list[np.ndarray] = []
        self.size = 0
        self.keys, self.counts = np.empty(0, np.int64), np.empty(0, np.int64)

    def add(self, numbers: np.ndarray) -> None:
        self.waiting.append(numbers)
        self.size += len(numbers)
        if self.size >= _GATHERED:
            self.settle()

    def settle(self) -> None:
        if self.waiting:
            keys, counts = np.unique(np.concatenate(self.waiting), return_counts=True)
            both, at = np.unique(np.concatenate((self.keys, keys)), return_inverse=True)
            self.counts = np.bincount(at, np.concatenate((self.counts, counts)), len(both)).astype(np.int64)
            self.keys, self.waiting, self.size = both, [], 0


def learn(docs: DataFrame, allowed: Column, text_col: str = "text", lang_col: str = "lang", size: int = PROFILE) -> Profiles:
    """Profiles from all rows with a language that satisfy ``allowed``."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[str, _Totals] = {}
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1)):
                totals.setdefault(lang.as_py(), _Totals()).add(ngrams(text.as_py()))
        for lang, total in totals.items():
            total.settle()
            for at in range(0, len(total.keys), 100_000):
                keys = total.keys[at : at + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(keys), pa.string()), pa.array(keys), pa.array(total.counts[at : at + 100_000])], names=["lang", "g", "n"])

    rows = docs.where(allowed).select(F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("text is not null and lang is not null")
    counts = rows.mapInArrow(released(count), "lang string, g long, n long").groupBy("lang", "g").agg(F.sum("n").alias("n"))
    order = Window.partitionBy("lang").orderBy(F.desc("n"), "g")
    found = counts.withColumn("place", F.row_number().over(order)).where(F.col("place") <= size).select("lang", "place", "g").collect()
    by_language: dict[str, list[int]] = {}
    for row in sorted(found, key=lambda r: (r["lang"], r["place"])):
        by_language.setdefault(row["lang"], []).append(row["g"])
    return Profiles(by_language, size)


def predict(docs: DataFrame, profiles: Profiles, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score), one row per document."""
    shared = docs.sparkSession.sparkContext.broadcast(profiles)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            found = [own.predict(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=["doc_id", "lang_pred", "score"])

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(released(run), f"doc_id {rows.schema[0].dataType.simpleString()}, lang_pred string, score double")


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op4: doc_id, held_out, lang_pred, score."""
    return predict(docs, learn(docs, ~held_out())).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
