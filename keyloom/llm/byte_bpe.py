"""Byte-level BPE: exact encoding in linear time by backtracking, and decoding.

Bytes are read as Latin-1 characters, so an Aho-Corasick automaton over strings finds, in one pass over a piece, every token in
it; the longest one at each start is kept. Encoding goes from left to right with the longest token, and takes the next
shorter prefix, or goes back, where a token can't stand next to the one before. Two tokens can if merging would not have joined
bytes across their border sooner; that depends on the two alone, so it is worked out once per pair and remembered. Ends that
proved dead are marked, so that no position is tried twice with the same end. The result is what applying merges by rank gives.

A table of tokens by rank is a vocabulary of fixed size; it is broadcast. Workers keep the ids of pieces and the pairs of tokens they
met, up to documented numbers, after which they forget all of them; results don't depend on it.

Null and empty texts have no ids. Every other text is encoded whole, whatever its length.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.llm.common import released

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Pieces, and pairs of tokens, that a worker remembers, and the length up to which it does pieces.
REMEMBERED, REMEMBERED_PAIRS, REMEMBERED_CHARS = 400_000, 400_000, 48


@lru_cache(maxsize=4)
def load_ranks(path: str) -> tuple[bytes, ...]:
    """Tokens by rank, from a file of base64 tokens and ranks."""
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}
    tokens = sorted(ranks, key=ranks.__getitem__)
    if [ranks[t] for t in tokens] != list(range(len(tokens))):
        raise ValueError("ranks must count up from 0 without gaps")
    return tuple(tokens)


@lru_cache(maxsize=1)
def unknown_characters() -> str:
    """A character class of what ``regex`` calls a letter or number and tiktoken's matcher doesn't: their Unicode versions differ."""
    found: list[list[int]] = []
    for name in (r"\p{L}", r"\p{N}"):
        theirs = tiktoken.Encoding("bytes", pat_str=name, mergeable_ranks={bytes([i]): i for i in range(256)}, special_tokens={})
        ours = regex.compile(name)
        for at in range(0, 0x110000, 0x100):
            if 0xD800 <= at < 0xE000 or bytes(theirs.encode_ordinary(part := "".join(map(chr, range(at, at + 0x100))))) == "".join(ours.findall(part)).encode():
                continue
            for c in part:
                if ours.match(c) and not theirs.encode_ordinary(c):
                    if found and found[-1][1] == ord(c) - 1:
                        found[-1][1] = ord(c)
                    else:
                        found.append([ord(c)] * 2)
    return "[" + "".join(rf"\U{a:08x}-\U{b:08x}" for a, b in found) + "]" if found else ""


class Codec:
    """Encoder and decoder for one vocabulary and one pattern that cuts texts into pieces; ``unknown``: a class of characters that are neither letters nor numbers to it."""

    def __init__(self, tokens: tuple[bytes, ...], pattern: str = public_tokenizers.PATTERN, unknown: str | None = None):
        self.ascii_pattern = regex.compile(pattern)
        if unknown := unknown_characters() if unknown is None else unknown:
            pattern = regex.sub(r"\[\^[^\]]*\]", lambda m: m[0].replace(r"\p{L}", "\1").replace(r"\p{N}", "\2"), pattern)
            pattern = pattern.replace(r"\p{L}", rf"[\p{{L}}--{unknown}]").replace(r"\p{N}", rf"[\p{{N}}--{unknown}]")
            pattern = pattern.replace("\1", rf"[\p{{L}}--{unknown}]").replace("\2", rf"[\p{{N}}--{unknown}]")
        self.tokens, self.pattern = tokens, regex.compile(pattern, regex.V1 if unknown else 0)
        self.rank = {t: i for i, t in enumerate(tokens)}
        self.length = [len(t) for t in tokens]
        self.halves = [self._last_merge(t) for t in tokens]
        self.automaton = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        self.shorter = [-1] * len(tokens)
        for i, token in enumerate(tokens):
            if self.halves[i] is None:
                continue  # merging never makes it; only a piece that equals it has its id
            self.automaton.add_word(token.decode("latin-1"), i)
            for n in range(len(token) - 1, 0, -1):
                j = self.rank.get(token[:n], -1)
                if j >= 0 and self.halves[j] is not None:
                    self.shorter[i] = j
                    break
        self.automaton.make_automaton()
        self.pairs: dict[int, bool] = {}
        self.seen = _Pieces(self)
        self.of_id = {str(i): t for i, t in enumerate(tokens)}

    def _last_merge(self, token: bytes) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; a byte is its own halves; None if merging ends otherwise."""
        rank = self.rank
        if len(token) == 1:
            return rank[token], rank[token]
        parts = [token[i : i + 1] for i in range(len(token))]
        while len(parts) > 2:
            best = min(range(len(parts) - 1), key=lambda i: rank.get(parts[i] + parts[i + 1], 1 << 60))
            if parts[best] + parts[best + 1] not in rank:
                return None
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return rank[parts[0]], rank[parts[1]]

    def fits(self, a: int, b: int) -> bool:
        """Whether token b can follow token a in the result of merging."""
        key = a << 32 | b
        if (known := self.pairs.get(key)) is None:
            if len(self.pairs) >= REMEMBERED_PAIRS:
                self.pairs.clear()
            known = self.pairs[key] = self._fits(a, b)
        return known

    def _fits(self, a: int, b: int) -> bool:
        """Takes the two tokens apart, the later merge first, and asks at each step if the border would have been merged by then."""
        limit, halves, tokens, rank = 1 << 60, self.halves, self.tokens, self.rank
        while True:
            if rank.get(tokens[a] + tokens[b], 1 << 60) < limit:
                return False
            whole = [self.length[a] == 1, self.length[b] == 1]
            if all(whole):
                return True
            if not whole[0] and (whole[1] or a > b):
                limit, a = a, halves[a][1]
            else:
                limit, b = b + 1, halves[b][0]

    def piece(self, raw: bytes) -> list[int]:
        """The ids of one piece."""
        if (known := self.rank.get(raw)) is not None:
            return [known]
        n, length, shorter, fits = len(raw), self.length, self.shorter, self.fits
        longest = [-1] * n
        for end, i in self.automaton.iter(raw.decode("latin-1")):
            longest[end + 1 - length[i]] = i
        open_ends = bytearray(b"\1") * (n + 1)
        ids: list[int] = []
        at, i = 0, longest[0]
        while at < n:
            end = at + length[i]
            if open_ends[end] and (not ids or fits(ids[-1], i)):
                ids.append(i)
                at = end
                i = longest[at] if at < n else -1
            elif shorter[i] >= 0:
                i = shorter[i]
            else:
                open_ends[at] = 0
                i = ids.pop()
                at -= length[i]
        return ids

    def encode_text(self, text: str | None) -> str:
        """The decimal ids of a text, joined by commas."""
        if not text:
            return ""
        return ",".join(map(self.seen.__getitem__, (self.ascii_pattern if text.isascii() else self.pattern).findall(text)))

    def encode(self, text: str | None) -> np.ndarray:
        """The ids of a text."""
        found = self.encode_text(text)
        return np.fromstring(found, np.int32, sep=",") if found else np.empty(0, np.int32)

    def decode_text(self, ids: str) -> bytes:
        return b"".join(map(self.of_id.__getitem__, ids.split(","))) if ids else b""

    def decode(self, ids) -> bytes:
        tokens = self.tokens
        return b"".join([tokens[i] for i in ids])


class _Pieces(dict):
    """Piece -> its ids as text; bounded."""

    def __init__(self, codec: Codec):
        super().__init__()
        self.codec = codec

    def __missing__(self, piece: str) -> str:
        ids = ",".join(map(str, self.codec.piece(piece.encode("utf-8"))))
        if len(piece) <= REMEMBERED_CHARS:
            if len(self) >= REMEMBERED:
                self.clear()
            self[piece] = ids
        return ids


_codecs: dict[tuple[int, str], Codec] = {}


def codec(tokens: tuple[bytes, ...], pattern: str) -> Codec:
    """One codec for each vocabulary in a process, kept across tasks."""
    key = hash(tokens), pattern
    if key not in _codecs:
        _codecs.clear()
        _codecs[key] = Codec(tokens, pattern)
    return _codecs[key]


def _mapped(docs: DataFrame, schema: str, row, id_col: str, value_col: str, kind: str, vocabulary: str | None, pattern: str, forget: bool = True) -> DataFrame:
    """row(codec, value) -> the columns after the id. ``forget``: pieces are remembered for one task only, and the memory goes to later stages."""
    shared = docs.sparkSession.sparkContext.broadcast(load_ranks(vocabulary or public_tokenizers.path(VOCABULARY)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(shared.value, pattern)
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                columns = list(zip(*(row(own, x.as_py()) for x in part.column(1))))
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, columns)], names=names)
        if forget:
            own.seen.clear()
            own.pairs.clear()

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(value_col).cast(kind).alias("value"))
    names = ["doc_id", *(x.split()[0] for x in schema.split(", "))]
    return rows.mapInArrow(released(run), f"doc_id {rows.schema[0].dataType.simpleString()}, {schema}")


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """(doc_id, n_tokens long, ids array<int>), one row per document. ``vocabulary``: path of a rank file that the driver can read."""

    def row(own: Codec, text: str | None):
        ids = own.encode(text)
        return len(ids), ids

    return _mapped(docs, "n_tokens long, ids array<int>", row, id_col, text_col, "string", vocabulary, pattern)


def decode(rows: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", vocabulary: str | None = None) -> DataFrame:
    """(doc_id, bytes binary): the bytes of the ids; null ids give no bytes."""
    return _mapped(rows, "bytes binary", lambda own, ids: (own.decode(ids or ()),), id_col, ids_col, "array<int>", vocabulary, public_tokenizers.PATTERN)


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op2: doc_id, n_tokens, ids_sha256, decoded_sha256."""

    def row(own: Codec, text: str | None):
        ids = own.encode_text(text)
        return ids.count(",") + 1 if ids else 0, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(own.decode_text(ids)).hexdigest()

    return _mapped(docs, "n_tokens long, ids_sha256 string, decoded_sha256 string", row, "doc_id", "text", "string", None, public_tokenizers.PATTERN, forget=False)
