"""Secret scan: base patterns, and a character convolutional network in numpy over every candidate and its context.

Candidates are all runs of token characters of 16 or more that have a letter and a digit. The network sees a candidate's
characters between those before and after it, each with a flag of whether it is inside; two convolutions' maxima and means over
the inside and over all feed a logistic unit. It is trained on labelled findings: those that a seeded generator
makes (secrets of many kinds among words and assignments, and look-alikes: commit ids, checksums, UUIDs, paths, names,
numbers), and candidates inside base findings of documents that it may learn from, as secrets, FINDINGS at most by a hash of id and place
(a classifier's fit). A part of all is held out: on it a Platt curve calibrates the scores, and the threshold is the largest that still
finds the wanted share of the held-out secrets, and SLACK standard errors more. The generator's size is a parameter; the scan covers every text whole.

A candidate longer than INSIDE is seen in overlapping windows of that length, each between what is before and after the whole, and scores as the highest of them. Base findings always
stay, and the network judges every candidate, those that base findings touch, too; of such a one that it takes for no secret as a whole it also judges the parts of LEAST_PART or more
characters that base findings leave. Null and empty texts have no findings.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyloom.llm.common import released

#: The kinds of findings, in their order, and the base patterns of the query's contract.
KINDS = ("assign", "access", "hex", "cnn")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
LEAST_ASSIGNED, LEAST_ACCESS, LEAST_HEX = 6, 20, 24
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{16,}")
#: What the network sees: characters before the candidate, of it, and after it; windows of longer ones begin STRIDE characters apart.
BEFORE, INSIDE, AFTER, STRIDE = 28, 48, 8, 12
LEAST_PART = 16
EXAMPLES, FINDINGS, HELD_OUT, RECALL, SLACK = 16_000, 2_000, 0.25, 0.98, 3.0

_TOKEN_BYTES = bytes(c if chr(c) in "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-" else 32 for c in range(256))
_ASSIGN_WORDS = (b"passw", b"secret", b"token", b"api")
_WIDTH = BEFORE + INSIDE + AFTER
_SYMBOLS = 100


# --- labelled findings -------------------------------------------------------------------------------------------------


def _token(r: random.Random, alphabet: str, low: int, high: int) -> str:
    return "".join(r.choices(alphabet, k=r.randint(low, high)))


_HEX, _UPPER, _LOWER, _DIGITS = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
_MIXED = _UPPER + _LOWER + _DIGITS


def _secret(r: random.Random) -> tuple[str, str, str]:
    """Text before, the secret, text after."""
    value = r.choice((
        lambda: _token(r, _HEX, 32, 64), lambda: _token(r, _MIXED, 20, 48), lambda: _token(r, _MIXED + "+/", 28, 64) + r.choice(("", "=", "==")),
        lambda: r.choice(("ghp_", "gho_", "glpat-", "sk_live_", "sk-", "xoxb-", "pk_live_", "npm_")) + _token(r, _MIXED, 24, 40),
        lambda: "AKIA" + _token(r, _UPPER + _DIGITS, 16, 16), lambda: "AIza" + _token(r, _MIXED + "_-", 35, 35), lambda: "eyJ" + _token(r, _MIXED + "_-", 30, 80),
    ))()
    name = r.choice(("key", "auth", "authorization", "bearer", "access_key", "private_key", "client_secret", "credential", "pwd", "token", "secret", "password", "api_key", "session", "signing key", "webhook"))
    name = r.choice((str, str.upper, str.title))(name)
    before = r.choice((f"{name} = ", f"{name}: ", f'{name}="', f"{name} ", f"export {name}=", f'"{name}": "', f"{name}: Bearer ", "", ""))
    return before, value, r.choice(("", '"', "'", " ", "\n", ",", ";"))


def _look_alike(r: random.Random) -> tuple[str, str, str]:
    words = lambda k, join: join.join(_token(r, _LOWER, 3, 9) for _ in range(k))
    kind = r.randrange(11)
    if kind == 0:
        return r.choice(("commit ", "revision ", "git show ", "merge ", "tree ", "blob ")), _token(r, _HEX, 40, 40), r.choice(("", "\n", " ", "."))
    if kind == 1:
        return r.choice(("md5: ", "sha256: ", "sha1sum ", "checksum ", "digest=", "etag: ", "integrity sha512-")), _token(r, _HEX, 32, 64), r.choice(("", "  ", "\n"))
    if kind == 2:
        return r.choice(("", "id: ", "uuid ", "request ")), "-".join(_token(r, _HEX, n, n) for n in (8, 4, 4, 4, 12)), r.choice(("", " ", "."))
    if kind == 3:
        return r.choice(("", "see ", "https://" + words(1, "") + ".org")), "/" + words(r.randint(3, 5), "/") + r.choice(("", "/")) + str(r.randrange(3000)), r.choice(("", " ", "."))
    if kind == 4:
        return r.choice(("", "the ")), words(r.randint(3, 5), r.choice("_-")) + r.choice(("_", "-", "")) + str(r.randrange(100)), r.choice((" ", "(", "."))
    if kind == 5:
        return r.choice(("", "on ", "at ")), f"20{r.randrange(10, 30)}-{r.randrange(1, 13):02}-{r.randrange(1, 29):02}T{r.randrange(24):02}-{r.randrange(60):02}", r.choice(("", " ", "Z"))
    if kind == 6:
        return r.choice(("data:image/png;base64,", "base64,")), "iVBORw0KGgo" + _token(r, _MIXED + "+/", 20, 80), '"'
    if kind == 7:
        return "", "".join(w.title() for w in words(r.randint(3, 5), " ").split()) + r.choice(("", str(r.randrange(1000)))) + "0", r.choice((" ", "(", "."))
    if kind == 8:
        return r.choice(("", "no. ", "order ", "ref ")), _token(r, _DIGITS, 8, 18) + r.choice(("A", "x", "-b", "-eur")) + _token(r, _DIGITS, 6, 12), r.choice((" ", "."))
    if kind == 9:
        return "", "-".join(words(1, "") + str(r.randrange(10)) for _ in range(r.randint(3, 5))), r.choice((".js", ".css", " ", "\n"))
    return "", words(r.randint(1, 2), "") + "=" * r.randint(8, 20) + str(r.randrange(100)), r.choice(("\n", " "))


def labelled_findings(n: int = EXAMPLES, seed: int = 7) -> tuple[list[tuple[str, int, int]], np.ndarray]:
    """n (text, start, end) and whether each is a secret."""
    r = random.Random(seed)
    filler = lambda: " ".join("".join(r.choices(("th", "er", "on", "an", "re", "he", "in", "ed", "é", "ch", "un", "ü", "de", "la", "ó"), k=r.randint(1, 4))) for _ in range(r.randint(0, 6)))
    texts, labels = [], []
    for i in range(n):
        before, value, after = (_secret if i % 2 else _look_alike)(r)
        before = filler() + r.choice((" ", ". ", "\n", "")) + before
        text, start = before + value + after + " " + filler(), len(before)
        whole = (m.span() for m in CANDIDATE.finditer(text) if m.start() <= start < m.end())  # what the scan would take, with a name joined by a sign
        texts.append((text, *next(whole, (start, start + len(value)))))
        labels.append(i % 2)
    return texts, np.array(labels, np.float64)


# --- the network -------------------------------------------------------------------------------------------------------


def _codes(text: str) -> list[int]:
    return [c - 30 if 32 <= (c := ord(x)) < 127 else 1 if c in (9, 10, 13) else 98 for x in text]


def windows(found: list[tuple[str, int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols (0: nothing there) and flags of the characters inside, one row for each window of each (text, start, end), and which of ``found`` each is of."""
    owner = [(i, *piece) for i, (_, start, end) in enumerate(found) for piece in _pieces(start, end)]
    symbols, inside = np.zeros((len(owner), _WIDTH), np.int16), np.zeros((len(owner), _WIDTH), np.float32)
    for row, (i, a, b) in enumerate(owner):
        text, start, end = found[i]
        own = text[a:b]
        before, after = _codes(text[max(0, start - BEFORE) : start]), _codes(text[end : end + AFTER])
        symbols[row, BEFORE - len(before) : BEFORE] = before
        symbols[row, BEFORE : BEFORE + len(own)] = _codes(own)
        inside[row, BEFORE : BEFORE + len(own)] = 1
        symbols[row, BEFORE + len(own) : BEFORE + len(own) + len(after)] = after
    return symbols, inside, np.array([i for i, _, _ in owner], np.int64)


def _pieces(start: int, end: int) -> list[tuple[int, int]]:
    """The whole, or the windows of INSIDE characters that cover it; of windows after the first, each begins STRIDE later, the last at the end."""
    if end - start <= INSIDE:
        return [(start, end)]
    return [(a, a + INSIDE) for a in (*range(start, end - INSIDE, STRIDE), end - INSIDE)]


@dataclass
class Network:
    """Embedding, one convolution of width 5, pooled inside and over all, a logistic unit; then the Platt curve and the threshold."""

    weights: dict[str, np.ndarray]
    curve: tuple[float, float] = (1.0, 0.0)
    threshold: float = 0.5

    @classmethod
    def fresh(cls, seed: int = 3, embed: int = 12, filters: int = 48) -> Network:
        g = np.random.default_rng(seed)
        return cls({"e": g.normal(0, 0.3, (_SYMBOLS, embed)), "k": g.normal(0, 0.15, (5 * (embed + 1), filters)), "b": np.zeros(filters), "o": g.normal(0, 0.1, 4 * filters), "c": np.zeros(1)})

    def forward(self, symbols: np.ndarray, inside: np.ndarray):
        w = self.weights
        x = np.concatenate((w["e"][symbols], inside[:, :, None]), axis=2)
        x = np.pad(x, ((0, 0), (2, 2), (0, 0)))
        columns = np.concatenate([x[:, i : i + _WIDTH] for i in range(5)], axis=2)
        z = columns @ w["k"] + w["b"]
        a = np.maximum(z, 0)
        m = inside[:, :, None]
        within = a * m
        n = np.maximum(inside.sum(1), 1)[:, None]
        pooled = np.concatenate((within.max(1), within.sum(1) / n, a.max(1), a.mean(1)), axis=1)
        return pooled @ w["o"] + w["c"][0], (columns, z, a, within, n, pooled)

    def step(self, symbols, inside, y, state: dict, rate: float) -> None:
        w = self.weights
        logit, (columns, z, a, within, n, pooled) = self.forward(symbols, inside)
        d = (1 / (1 + np.exp(-logit)) - y) / len(y)
        grads = {"o": pooled.T @ d, "c": np.array([d.sum()])}
        f = len(w["b"])
        p = d[:, None] * w["o"]
        da = np.zeros_like(a)
        rows, cols = np.arange(len(y))[:, None], np.arange(f)[None, :]
        da[rows, within.argmax(1), cols] += p[:, :f]
        da += (p[:, f : 2 * f] / n)[:, None, :]
        da *= inside[:, :, None]
        da[rows, a.argmax(1), cols] += p[:, 2 * f : 3 * f]
        da += (p[:, 3 * f :] / _WIDTH)[:, None, :]
        da *= z > 0
        grads["k"] = np.tensordot(columns, da, axes=((0, 1), (0, 1)))
        grads["b"] = da.sum((0, 1))
        dc = da @ w["k"].T
        width = w["e"].shape[1] + 1
        dx = np.zeros((len(y), _WIDTH + 4, width))
        for i in range(5):
            dx[:, i : i + _WIDTH] += dc[:, :, i * width : (i + 1) * width]
        grads["e"] = np.zeros_like(w["e"])
        np.add.at(grads["e"], symbols.ravel(), dx[:, 2:-2, :-1].reshape(-1, width - 1))
        state["t"] = state.get("t", 0) + 1
        for name, grad in grads.items():
            m = state[name, 1] = 0.9 * state.get((name, 1), 0) + 0.1 * grad
            v = state[name, 2] = 0.999 * state.get((name, 2), 0) + 0.001 * grad**2
            w[name] = w[name] - rate * (m / (1 - 0.9 ** state["t"])) / (np.sqrt(v / (1 - 0.999 ** state["t"])) + 1e-8)

    def scores(self, found: list[tuple[str, int, int]]) -> np.ndarray:
        """Calibrated probabilities, for each the highest of its windows."""
        out = np.zeros(len(found))
        for at in range(0, len(found), 64):
            symbols, inside, owner = windows(found[at : at + 64])
            for k in range(0, len(owner), 512):
                logit, _ = self.forward(symbols[k : k + 512], inside[k : k + 512])
                np.maximum.at(out, at + owner[k : k + 512], 1 / (1 + np.exp(-(self.curve[0] * logit + self.curve[1]))))
        return out


@lru_cache(maxsize=4)
def trained(examples: int = EXAMPLES, recall: float = RECALL, seed: int = 7, epochs: int = 6, more: tuple[tuple[str, int, int], ...] = ()) -> Network:
    """Trains, calibrates and sets the threshold; the same for the same parameters. ``more``: secrets beside the generated ones."""
    found, y = labelled_findings(examples, seed)
    found, y = [*found, *more], np.concatenate((y, np.ones(len(more))))
    symbols, inside, owner = windows(found)
    order = np.random.default_rng(seed).permutation(len(y))
    held, fit = np.split(order, [int(len(y) * HELD_OUT)])
    fit, of_held = np.flatnonzero(np.isin(owner, fit)), np.flatnonzero(np.isin(owner, held))
    net, state = Network.fresh(), {}
    for epoch in range(epochs):
        for part in np.array_split(np.random.default_rng(seed + epoch).permutation(fit), max(1, len(fit) // 64)):
            net.step(symbols[part], inside[part], y[owner[part]], state, 0.004 * 0.6**epoch)
    highest = np.full(len(y), -np.inf)
    for p in np.array_split(of_held, max(1, len(of_held) // 512)):
        np.maximum.at(highest, owner[p], net.forward(symbols[p], inside[p])[0])
    logit = highest[held]
    a, b = 1.0, 0.0
    for _ in range(300):  # Platt: logistic regression on the one score
        d = 1 / (1 + np.exp(-(a * logit + b))) - y[held]
        a, b = a - 0.05 * (d * logit).mean(), b - 0.05 * d.mean()
    net.curve = (float(a), float(b))
    scores = 1 / (1 + np.exp(-(a * logit + b)))
    of_secrets = np.sort(scores[y[held] == 1])
    net.threshold = float(of_secrets[may_miss(len(of_secrets), recall)])
    return net


def may_miss(n: int, recall: float) -> int:
    """How many of n held-out secrets a threshold may miss, so that the recall among all is as wanted, SLACK standard errors of n aside."""
    return max(0, math.floor(n * (1 - recall) - SLACK * math.sqrt(n * recall * (1 - recall))))


def document_findings(docs: DataFrame, allowed: Column, id_col: str = "doc_id", text_col: str = "text", limit: int = FINDINGS) -> tuple[tuple[str, int, int], ...]:
    """(text, start, end) of candidates inside base findings of the rows that satisfy ``allowed``, with what the network sees around them; the first ``limit`` by a hash of the id and the place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for name, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                base = base_findings(text) if text else ()
                for a, b in candidates(text) if base else ():
                    if any(s <= a and b <= e + 1 for s, _, e in base):
                        low = max(0, a - BEFORE)
                        rows.append((hashlib.md5(f"{name}:{a}".encode()).hexdigest(), text[low : b + AFTER], a - low, b - low))
            yield pa.RecordBatch.from_pylist([dict(zip(("h", "text", "a", "b"), r)) for r in rows], schema=pa.schema([("h", pa.string()), ("text", pa.string()), ("a", pa.int64()), ("b", pa.int64())]))

    rows = docs.where(allowed).select(F.col(id_col).cast("string").alias("name"), F.col(text_col).cast("string").alias("text")).where("text is not null")
    found = rows.mapInArrow(released(run), "h string, text string, a long, b long").orderBy("h", "text", "a").limit(limit).collect()
    return tuple((r["text"], r["a"], r["b"]) for r in found)


def held_out(id_col: str = "doc_id") -> Column:
    """Documents that the network doesn't learn from: a fifth, by the id."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def learnt(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Network:
    """The network for these documents."""
    return trained(more=document_findings(docs, ~held_out(id_col), id_col, text_col))


# --- the scan ----------------------------------------------------------------------------------------------------------


def base_findings(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the base patterns, in order."""
    raw = text.encode("utf-8", "surrogatepass")
    found = []
    low = raw.lower()
    if any(w in low for w in _ASSIGN_WORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_ASSIGNED]
    if b"AKIA" in raw:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    if any(len(w) >= LEAST_HEX for w in raw.translate(_TOKEN_BYTES).split()):
        found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def candidates(text: str) -> list[tuple[int, int]]:
    """(start, end) of everything the network is asked about."""
    if not any(len(w) >= 16 and any(48 <= c < 58 for c in w) for w in text.encode("utf-8", "surrogatepass").translate(_TOKEN_BYTES).split()):
        return []
    return [(m.start(), m.end()) for m in CANDIDATE.finditer(text) if (any(c.isdigit() for c in m[0]) and any(c.isalpha() for c in m[0]))]


def _uncovered(text: str, start: int, end: int, base: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """The candidate, or the parts that base findings leave of it, without joining signs at their ends, that are candidates themselves."""
    touching = [(s, e) for s, _, e in base if s < end and start < e]
    if not touching:
        return [(start, end)]
    parts, at = [], start
    for s, e in [*touching, (end, end)]:
        if s > at:
            a, b = at, s
            while a < b and text[a] in "+/_=-":
                a += 1
            while a < b and text[b - 1] in "+/_-":
                b -= 1
            own = text[a:b]
            if b - a >= LEAST_PART and any(c.isdigit() for c in own) and any(c.isalpha() for c in own):
                parts.append((a, b))
        at = max(at, e)
    return parts


def findings(texts: list[str | None], net: Network) -> list[list[tuple[int, int, int, float]]]:
    """(start, kind, end, score) of each text, in order; base findings have score 1."""
    out, asked, owner = [], [], []
    for i, text in enumerate(texts):
        base = base_findings(text) if text else []
        out.append([(*f, 1.0) for f in base])
        for start, end in candidates(text) if text else ():
            parts = [p for p in _uncovered(text, start, end, base) if p != (start, end)]
            for a, b in [(start, end), *parts]:
                owner.append((i, a, b, (start, end)))
                asked.append((text, a, b))
    taken = None  # a candidate that is a finding as a whole: its parts come after it
    for (i, a, b, of), score in zip(owner, net.scores(asked) if asked else ()):
        if score >= net.threshold and taken != (i, of):
            out[i].append((a, 3, b, float(score)))
            taken = (i, of) if (a, b) == of else taken
    return [sorted(f) for f in out]


def _scanned(docs: DataFrame, schema: str, columns, id_col: str, text_col: str, net: Network | None) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(net or learnt(docs, id_col, text_col))
    names = ["doc_id", *(x.split()[0] for x in re.split(r", (?![^<]*>)", schema))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                found = findings(part.column(1).to_pylist(), shared.value)
                yield pa.RecordBatch.from_arrays([part.column(0), *columns(found)], names=names)

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(released(run), f"doc_id {rows.schema[0].dataType.simpleString()}, {schema}")


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", net: Network | None = None) -> DataFrame:
    """(doc_id, findings array<(kind, start, end, score)>), one row per document."""
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
    columns = lambda found: [pa.array([[{"kind": KINDS[k], "start": s, "end": e, "score": p} for s, k, e, p in f] for f in found], kind)]
    return _scanned(docs, "findings array<struct<kind: string, start: long, end: long, score: double>>", columns, id_col, text_col, net)


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op10."""

    def columns(found):
        spans = lambda f: ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e, _ in f)
        base = [[x for x in f if x[1] < 3] for f in found]
        counts = [pa.array([sum(x[1] == k for x in f) for f in base], pa.int64()) for k in range(3)]
        return [*counts, pa.array([hashlib.sha256(spans(f).encode()).hexdigest() for f in base]), pa.array([spans(f) for f in found], pa.string())]

    return _scanned(docs, "n_assign long, n_access long, n_hex long, base_sha256 string, spans string", columns, "doc_id", "text", None)


def redact(docs: DataFrame, text_col: str = "text", mark: str = "[SECRET]", net: Network | None = None, id_col: str = "doc_id") -> DataFrame:
    """The rows of ``docs``, all columns, with every finding in the text replaced by ``mark``; overlapping findings by one. Null texts stay null."""
    net = net or (learnt(docs, id_col, text_col) if id_col in docs.columns else trained())
    shared = docs.sparkSession.sparkContext.broadcast(net)
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                texts = part.column(place).to_pylist()
                clean = [_without(t, f, mark) if f else t for t, f in zip(texts, findings(texts, shared.value))]
                yield part.set_column(place, part.schema.field(place), pa.array(clean, part.schema.field(place).type))

    return docs.mapInArrow(released(run), docs.schema)


def _without(text: str, found: list[tuple[int, int, int, float]], mark: str) -> str:
    out, done = [], 0
    for start, _, end, _ in found:
        if start >= done:
            out += [text[done:start], mark]
        done = max(done, end)
    return "".join([*out, text[done:]])
