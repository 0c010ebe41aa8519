"""Embedding near duplicates by spherical-cap filters of a structured random product code.

Directions are product codes: after each of ROTATIONS seeded rotations a vector is cut into BLOCKS parts, each with its own codebook of random unit
vectors; every combination of one word from each is a filter, and a vector is in all filters whose inner product with it reaches
a level. The list of those is decoded block by block: a partial choice is kept only while the best words of the blocks left can
still lift it to the level, so work follows the length of the list and not the number of filters. Vectors that share a filter meet, and
are verified by their cosine in double precision.

The number of filters follows the number of vectors, so that a filter keeps about the same few of them at any size; the level follows
from it, and the list is as long as the wanted recall of pairs at the threshold asks (``Code.planned``). Pairs of higher cosine share more filters.

Equal vectors are one node with a count. A filter with more than BUCKET nodes is cut into parts by a hash, and every two parts
meet in a task of their own; no task holds more than two parts. A pair counts only in the least of the filters that both have, so it counts
once, and tasks give a row for each node (its links there, and a node it is connected with), never the pairs.

Only vectors of one length are compared; each length that several have gets a code of its own. Vectors that are null, empty, zero, or hold null or non-finite components link with nothing and are kept.
So are rows with a null id, whose component is null.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache, reduce
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.llm.common import components, groups, released, written

THRESHOLD = 0.9
RECALL = 0.98
ROTATIONS, BLOCKS = 16, 2
#: Random pairs from which the level is taken.
PAIRS = 1_500
#: What a task gathers before it counts.
HELD_NODES, HELD_PAIRS = 5_000, 1_000_000
#: Vectors that a filter should hold if directions were spread evenly; nodes of a part.
PER_FILTER, BUCKET = 4.0, 1_000


@dataclass(frozen=True)
class Code:
    """ROTATIONS product codes of ``words`` codewords in each block, and the level a filter's inner product has to reach."""

    dim: int
    words: int
    level: float
    seed: int = 11

    @classmethod
    @lru_cache(maxsize=8)
    def planned(cls, n: int, dim: int, threshold: float = THRESHOLD, recall: float = RECALL) -> Code:
        """For n vectors: so many words that a filter holds about PER_FILTER of them, and the highest level that keeps the recall.

        How often a pair shares a filter depends on where it lies in the code, so the level is taken from decoding a seeded sample of random pairs at
        the threshold; the normal approximation, good enough for lengths, only gives the number of words.
        """
        normal = NormalDist()
        for words in (round(8 * 1.2**i) for i in range(28)):
            filters = ROTATIONS * float(words) ** BLOCKS
            t = _bisect(lambda t: 1 - math.exp(-filters * _both_above(t, threshold, normal) / 2) >= recall, 0.0, 8.0, 12)
            if n * (1 - normal.cdf(t)) <= PER_FILTER:
                break
        g = np.random.default_rng(5)
        x, y = g.normal(size=(2, PAIRS, dim))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        y -= (x * y).sum(axis=1, keepdims=True) * x
        y = threshold * x + math.sqrt(1 - threshold**2) * y / np.linalg.norm(y, axis=1, keepdims=True)

        def holds(level: float) -> bool:
            code = cls(dim, words, level)
            books = code.books()
            (r, f), (q, h) = decode(code, x, books), decode(code, y, books)
            space = len(books) * words ** len(books[0][1])
            shared = np.intersect1d(r * space + f, q * space + h, assume_unique=True) // space
            return len(np.unique(shared)) >= recall * PAIRS

        return cls(dim, words, _bisect(holds, max(0.0, t / math.sqrt(dim) - 0.12), t / math.sqrt(dim) + 0.1, 9))

    def books(self) -> list[tuple[np.ndarray, list[np.ndarray]]]:
        """Each rotation, and its blocks' words; a filter's direction has length 1."""
        g = np.random.default_rng(self.seed)
        widths = [len(p) for p in np.array_split(np.arange(self.dim), min(BLOCKS, self.dim))]
        out = []
        for _ in range(ROTATIONS):
            rotation, _ = np.linalg.qr(g.normal(size=(self.dim, self.dim)))
            blocks = [g.normal(size=(self.words, width)) for width in widths]
            out.append((rotation, [b / np.linalg.norm(b, axis=1, keepdims=True) * math.sqrt(b.shape[1] / self.dim) for b in blocks]))
        return out


def _bisect(holds, low: float, high: float, steps: int = 40) -> float:
    """The highest value between the two for which ``holds`` is true, as far as steps go."""
    for _ in range(steps):
        middle = (low + high) / 2
        low, high = (middle, high) if holds(middle) else (low, middle)
    return low


def _both_above(t: float, rho: float, normal: NormalDist, steps: int = 120) -> float:
    """The chance that two standard normals with correlation rho are both above t."""
    xs = np.linspace(t, t + 5, steps)
    density = np.exp(-xs * xs / 2) / math.sqrt(2 * math.pi)
    tail = np.array([1 - normal.cdf((t - rho * x) / math.sqrt(1 - rho * rho)) for x in xs])
    y = density * tail
    return float(((y[1:] + y[:-1]) / 2).sum() * (xs[1] - xs[0]))


def decode(code: Code, unit: np.ndarray, books: list | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(row, filter) of all filters that each unit vector is in, by row and filter; a vector in none goes to the nearest of each rotation."""
    rows, numbers = [], []
    books = books or code.books()
    space = code.words ** len(books[0][1])
    for i, (rotation, parts) in enumerate(books):
        row, number = _decode(code, unit @ rotation, parts)
        rows.append(row)
        numbers.append(number + i * space)
    if len(lost := np.setdiff1d(np.arange(len(unit)), np.concatenate(rows))):
        for i, (rotation, parts) in enumerate(books):
            turned, nearest, at = unit[lost] @ rotation, np.zeros(len(lost), np.int64), 0
            for book in parts:
                nearest = nearest * code.words + (turned[:, at : at + book.shape[1]] @ book.T).argmax(axis=1)
                at += book.shape[1]
            rows.append(lost)
            numbers.append(nearest + i * space)
    row, number = np.concatenate(rows), np.concatenate(numbers)
    by = np.lexsort((number, row))
    return row[by], number[by]


def _decode(code: Code, turned: np.ndarray, parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    at, scores = 0, []
    for book in parts:
        scores.append(turned[:, at : at + book.shape[1]] @ book.T)
        at += book.shape[1]
    best_left = np.zeros((len(turned), len(parts) + 1))
    for k in range(len(parts) - 1, -1, -1):
        best_left[:, k] = best_left[:, k + 1] + scores[k].max(axis=1)
    row, total, number = np.arange(len(turned)), np.zeros(len(turned)), np.zeros(len(turned), np.int64)
    for k, own in enumerate(scores):
        order = np.argsort(-own, axis=1, kind="stable")
        ranked = np.take_along_axis(own, order, axis=1)
        kept = []
        for part in np.array_split(np.arange(len(row)), max(1, len(row) // 20_000)):
            needed = code.level - total[part] - best_left[row[part], k + 1]
            kept.append((ranked[row[part]] >= needed[:, None]).sum(axis=1))
        n = np.concatenate(kept)
        which = np.repeat(np.arange(len(row)), n)
        nth = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
        r = row[which]
        row, total, number = r, total[which] + ranked[r, nth], number[which] * code.words + order[r, nth]
    return row, number


def usable(column: pa.Array, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """The places of the usable vectors of a list column, and these as a matrix of the column's own precision."""
    kind = np.float32 if column.type.value_type == pa.float32() else np.float64
    lengths = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(kind)
    starts = np.cumsum(lengths) - lengths
    places = np.nonzero(lengths == dim)[0]
    if not dim or not len(places):
        return places[:0], np.empty((0, dim), kind)
    x = flat[starts[places][:, None] + np.arange(dim)]
    peak = np.abs(x).max(axis=1)
    good = np.isfinite(peak) & (peak > 0)
    return places[good], x[good]


def unit_vectors(x: np.ndarray) -> np.ndarray:
    """Rows in double precision at length 1."""
    x = x.astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _linked(x: np.ndarray, y: np.ndarray | None, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows at the threshold: of x and y, or within x."""
    at, to = np.nonzero(x @ (x if y is None else y).T >= threshold)
    return (at[at < to], to[at < to]) if y is None else (at, to)


class _Meeting:
    """Links that the filters of one task find, until it is known which of them the filter may count."""

    def __init__(self, code: Code, threshold: float):
        self.code, self.books, self.threshold = code, code.books(), threshold
        self.vectors: dict[int, np.ndarray] = {}
        self.waiting: list[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        self.pairs = 0

    def add(self, number: int, within: bool, part: np.ndarray, node: np.ndarray, copies: np.ndarray, x: np.ndarray) -> None:
        """The nodes of a filter, or of two parts of one."""
        if within:
            a, b = _linked(x, None, self.threshold)
        else:
            low, high = np.nonzero(part == part.min())[0], np.nonzero(part != part.min())[0]
            if not len(high):
                return
            a, b = _linked(x[low], x[high], self.threshold)
            a, b = low[a], high[b]
        if len(a):
            used, at = np.unique(np.concatenate((a, b)), return_inverse=True)
            self.vectors.update(zip(node[used].tolist(), x[used]))
            self.waiting.append((number, node[used], copies[used], at[: len(a)], at[len(a) :]))
            self.pairs += len(a)

    def counted(self) -> Iterator[pa.RecordBatch]:
        """(node, links, other) of the links gathered so far that have no lesser filter in common."""
        nodes = np.fromiter(self.vectors, np.int64, len(self.vectors))
        if not len(nodes):
            return
        row, filters = decode(self.code, np.stack(list(self.vectors.values())), self.books)
        ends = np.searchsorted(row, np.arange(len(nodes) + 1))
        place = {n: i for i, n in enumerate(nodes.tolist())}
        for number, node, copies, a, b in self.waiting:
            lists = [filters[ends[i] : ends[i + 1]] for i in map(place.__getitem__, node.tolist())]
            lower = [f[: np.searchsorted(f, number)] for f in lists]
            columns, column = np.unique(np.concatenate(lower), return_inverse=True)
            has = np.zeros((len(node), len(columns)), np.float32)
            has[np.repeat(np.arange(len(node)), [len(f) for f in lower]), column] = 1
            first = (has @ has.T)[a, b] == 0
            if first.any():
                yield _by_node(node, copies, a[first], b[first])
        self.vectors, self.waiting, self.pairs = {}, [], 0


def _by_node(node: np.ndarray, copies: np.ndarray, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    """Each node's links, and a node that they connect it with, the same for all that are connected."""
    n = len(node)
    links = np.bincount(a, copies[b], n) + np.bincount(b, copies[a], n)
    root = np.arange(n)
    while True:
        after = root.copy()
        least = np.minimum(root[a], root[b])
        np.minimum.at(after, a, least)
        np.minimum.at(after, b, least)
        after = after[after]
        if (after == root).all():
            break
        root = after
    rows = np.nonzero(links > 0)[0]
    return pa.RecordBatch.from_pydict({"node": node[rows], "links": links[rows].astype(np.int64), "other": node[root[rows]]})


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", threshold: float = THRESHOLD, recall: float = RECALL, per_filter_rows: int = BUCKET) -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row per vector."""
    v = F.col(vector_col) if vectors.schema[vector_col].dataType.simpleString() == "array<float>" else F.col(vector_col).cast("array<double>")
    rows, _ = written(vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")), "vectors")
    copies, _ = written(rows.where("vec_id is not null").groupBy("v").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies")), "copies")
    several = F.sum("copies") > 1  # a length that only one vector has gives no links; a length is a pass of its own
    sizes = copies.where("size(v) > 0").groupBy(F.size("v").alias("dim")).agg(F.count("*").alias("n"), several.alias("several")).where("several").orderBy("dim").collect()
    if not sizes:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    lengths = [_links_of_length(copies.where(F.size("v") == row["dim"]), row["dim"], row["n"], threshold, recall, per_filter_rows) for row in sizes]
    nodes, met = (reduce(DataFrame.unionByName, tables) for tables in zip(*lengths))
    links = met.groupBy("node").agg(F.sum("links").alias("links"))
    roots = components(met.select(F.col("node").alias("a"), F.col("other").alias("b"))).withColumnRenamed("node", "r_node")
    placed = nodes.select("node", "copies").join(links.withColumnRenamed("node", "l_node"), F.col("node") == F.col("l_node"), "left").join(roots, F.col("node") == F.col("r_node"), "left")
    placed = placed.select("node", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "node").alias("root"))
    least = placed.groupBy("root").agg(F.min("node").alias("component_id")).withColumnRenamed("root", "of")
    classes = placed.join(least, F.col("root") == F.col("of")).select("node", "n_links", "component_id")
    of_vector = copies.select(F.col("v").alias("c_v"), F.col("node").alias("c_node")).join(classes, F.col("c_node") == F.col("node"), "left")
    of_vector, _ = written(of_vector.select("c_v", "n_links", "component_id"), "classes")
    done = rows.join(of_vector, F.col("v").eqNullSafe(F.col("c_v")) & F.col("vec_id").isNotNull(), "left")
    component = F.when(F.col("vec_id").isNotNull(), F.coalesce("component_id", "vec_id"))
    return done.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def _links_of_length(copies: DataFrame, dim: int, n: int, threshold: float, recall: float, per_filter_rows: int) -> tuple[DataFrame, DataFrame]:
    """(node, copies) of the usable vectors of that length, and (node, links, other) of those that have links."""
    code = Code.planned(n, dim, threshold, recall)

    def decoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        books = code.books()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                places, raw = usable(part.column(0), dim)
                row, number = decode(code, unit_vectors(raw), books) if len(raw) else (np.empty(0, np.int64),) * 2
                ends = np.searchsorted(row, np.arange(len(raw) + 1))
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(number, pa.int64()))
                taken = part.take(pa.array(places, pa.int64()))
                yield pa.RecordBatch.from_arrays([taken.column(1), taken.column(2), pa.array([v.tobytes() for v in raw], pa.binary()), lists], names=["node", "copies", "x", "filters"])

    nodes, _ = written(copies.select("v", "node", "copies").mapInArrow(released(decoded), "node long, copies long, x binary, filters array<long>"), "nodes")
    members = nodes.select("node", "copies", "x", F.explode("filters").alias("filter"))
    held = nodes.select(F.explode("filters").alias("f")).groupBy("f").agg(F.count("*").alias("held")).where("held > 1")
    parts = F.ceil(F.col("held") / per_filter_rows).cast("int")
    members = members.join(held, F.col("filter") == F.col("f")).withColumn("parts", parts).withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    meets = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least(j, F.col("part")).alias("low"), F.greatest(j, F.col("part")).alias("high")))
    members = members.select("filter", "part", "node", "copies", "x", F.explode(meets).alias("m")).select("filter", "m.low", "m.high", "part", "node", "copies", "x")
    keys = ["filter", "low", "high"]

    kind = np.float32 if copies.schema["v"].dataType.simpleString() == "array<float>" else np.float64

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        meeting = _Meeting(code, threshold)
        for group in groups(batches, keys):
            if group.num_rows > 1:
                number = lambda c: group.column(c).to_numpy()
                x = unit_vectors(np.frombuffer(b"".join(group.column("x").to_pylist()), kind).reshape(-1, dim))
                meeting.add(group.column("filter")[0].as_py(), group.column("low")[0] == group.column("high")[0], number("part"), number("node"), number("copies"), x)
                if len(meeting.vectors) > HELD_NODES or meeting.pairs > HELD_PAIRS:
                    yield from meeting.counted()
        yield from meeting.counted()

    met = members.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(released(meet), "node long, links long, other long")
    met, _ = written(met, "met")
    return nodes.select("node", "copies"), met


def digest(vectors: DataFrame) -> DataFrame:
    """The rows of query op3: vec_id, n_links, component_id, kept."""
    return near_duplicates(vectors)
