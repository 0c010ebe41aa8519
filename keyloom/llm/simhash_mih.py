"""SimHash near duplicates by multi-index hashing.

A text's fingerprint has bit i set if over half of its shingle hashes have. Fingerprints are cut into segments; if two of them
differ in ``radius`` bits or fewer, some segment agrees up to its share of these (``Cut``). So each distinct fingerprint goes into a
table for each segment, and looks up, in each, the small ball around its segment. Of two segments that differ, one is the greater number, so a ball
needs only the segment itself and lesser numbers. How many segments there are follows from the number of fingerprints: few long ones with larger
balls for many, so that look-ups and what they find stay in balance. A pair is verified by its complete distance inside the join
and is given by the first segment that finds it, so that joins give links, once each, and no candidates.

A group of thousands of near copies must not make all of its pairs. So every table's equal segments are first linked to a few leaders of their
own only, and look-ups then meet only what isn't in the same group yet.

``similar_groups`` takes these steps for a similarity of shingle sets, for which 64 bits are too few: several words of 64 bits over the distinct shingles.
A similarity is an expected share of differing bits, to which DEVIATIONS standard deviations are added. Bits only make candidates, and
candidates only make clusters: texts far less similar than asked are put together by leaders first (no pairs are made inside such a cluster), then
look-ups add what lies in different clusters. At last the shingle sets of a cluster meet in one task (a large one's in blocks), which counts exactly what any two have in common and
gives one row for each set, never pairs. So every link is as similar as asked, and two texts as similar as that lie in one cluster with a chance of FOUND
by the segments alone. Blocks of a large cluster first meet its leaders, and then only sets that aren't in its largest group are compared with the rest. Here a node is a distinct set of shingles.

Equal fingerprints are one node, so groups of copies never make pairs. Null and empty texts have fingerprint zero and
are linked like any other (``keep_one`` lets null texts pass). Rows with a null id get a component by their fingerprint's other rows (null if there are none).
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from keyloom.llm.common import components, groups, released, written

WORDS = 4
RADIUS = 4
SIMILAR_WORDS, SIMILARITY = 5, 0.8
#: Chance that the segments find a pair of just the similarity asked; deviations that its differing bits may be off; sets a bucket of a segment may hold if they were spread evenly.
FOUND, DEVIATIONS, PER_BUCKET = 0.98, 3, 64
#: Bits of the shortest segments, and words of the shortest wide fingerprints.
LEAST_WIDTH, LEAST_WORDS = 16, 8
#: Words of a wide fingerprint that go with its segments and are compared inside the join; a pair of unlike sets has 64 differing bits of them, give or take 6.
HEAD_WORDS = 2
#: The part of the similarity asked that puts two sets into one cluster when one of them is a leader.
SOFT = 0.5
#: Sets, and shingles, of a part of a large cluster; two parts and the leaders meet in a task.
PART_SETS, PART_SHINGLES = 1_000, 1_000_000
#: Shingles in more sets of a block than this are counted by a matrix product, others by their pairs.
COMMON = 16
#: Tables of up to so many rows (16 bytes each, some 50 in memory) are broadcast, larger ones are joined by a shuffle.
BROADCAST_NODES = 1_000_000


@dataclass(frozen=True)
class Cut:
    """Segments of a fingerprint of 64 bits: (first bit, width, radius of the ball that is looked up)."""

    segments: tuple[tuple[int, int, int], ...]

    @classmethod
    def planned(cls, n: int, radius: int) -> Cut:
        """The cut with the least work for n fingerprints: look-ups, and what each finds if fingerprints were spread evenly.

        Of s segments, if all were off by more than radius // s bits, or by that many for those after the first radius % s + 1, the sum would be above the radius.
        """
        if not 0 <= radius <= 12:
            raise ValueError("a radius of 0 to 12")
        best = None
        for s in range(2, radius + 2):
            share, first = radius // s, radius % s + 1
            ends = [64 * i // s for i in range(s + 1)]
            segments = tuple((a, b - a, share if i < first else share - 1) for i, (a, b) in enumerate(zip(ends, ends[1:])) if i < first or share > 0)
            work = sum(sum(math.comb(w, i) for i in range(ball + 1)) * (1 + n / 2.0**w) for _, w, ball in segments)
            if best is None or work < best[0]:
                best = work, segments
        return cls(best[1] if best else ((0, 64, 0),))

    def segment(self, fp: Column, k: int) -> Column:
        first, width, _ = self.segments[k]
        return F.shiftrightunsigned(fp, first).bitwiseAND(F.lit((1 << width) - 1)) if width < 64 else fp

    def masks(self, k: int) -> list[int]:
        _, width, ball = self.segments[k]
        return [sum(1 << i for i in bits) for r in range(ball + 1) for bits in combinations(range(width), r)]


@dataclass(frozen=True)
class Wide:
    """``count`` segments of ``width`` bits, as many in each word of 64 as fit, for a similarity of sets."""

    width: int
    count: int
    similarity: float

    @classmethod
    def planned(cls, n: int, similarity: float) -> Wide:
        """Segments as wide as n sets need to leave PER_BUCKET in a bucket, and as many as find a pair of that similarity, up to a bit, with a chance of FOUND."""
        width = min(32, max(LEAST_WIDTH, math.ceil(math.log2(max(1, n) / PER_BUCKET))))
        off = differing(similarity)
        hit = (1 - off) ** width + width * off * (1 - off) ** (width - 1)
        return cls(width, math.ceil(math.log(1 - FOUND) / math.log(1 - hit)) if hit < 1 else 1, similarity)

    @property
    def words(self) -> int:
        return max(LEAST_WORDS, -(-self.count // (64 // self.width)))

    def allowed(self, similarity: float, words: int, deviations: float) -> int:
        """Differing bits in so many words that sets of a similarity may have."""
        off = differing(similarity)
        return int(64 * words * off + deviations * math.sqrt(64 * words * off * (1 - off)))

    def key(self, names: list[str], j: int) -> Column:
        """The number of segment j, with j above it."""
        per = 64 // self.width
        return F.shiftrightunsigned(F.col(names[j // per]), self.width * (j % per)).bitwiseAND(F.lit((1 << self.width) - 1)) + F.lit(j << 40)


def differing(similarity: float) -> float:
    """The expected share of differing bits of two sets of like size with that Jaccard similarity."""
    return math.acos(min(1.0, 2 * similarity / (1 + similarity))) / math.pi


def fingerprint(text: str | None, words: int = WORDS) -> int:
    """The 64-bit SimHash (unsigned) of the word shingles of ``text``, repeats included; 0 if it has no word."""
    return int(_majority(_hashes(text, words)[:, None])[0])


def _hashes(text: str | None, words: int) -> np.ndarray:
    """XXH64 of each shingle; a text of fewer words is one shingle."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not found:
        return np.empty(0, np.uint64)
    joined = b" ".join(found)
    ends = np.cumsum(np.fromiter(map(len, found), np.int64, len(found)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    last = ends[words - 1 :] if len(found) >= words else ends[-1:]
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts.tolist(), last.tolist())), np.uint64, len(last))


def _majority(hashes: np.ndarray) -> np.ndarray:
    """Words of 64 bits, set where over half of the rows (one column for each word) have them set."""
    n, width = hashes.shape
    total = np.zeros(64 * width, np.int64)
    for at in range(0, n, 255 * 16):
        bits = np.unpackbits(np.ascontiguousarray(hashes[at : at + 255 * 16], "<u8").view(np.uint8).reshape(-1, 8 * width), axis=1, bitorder="little")
        total += np.add.reduceat(bits, np.arange(0, len(bits), 255), axis=0, dtype=np.uint8).sum(axis=0, dtype=np.int64)
    return np.packbits((2 * total > n).astype(np.uint8), bitorder="little").view("<u8")


def wide_fingerprint(hashes: np.ndarray, words: int) -> np.ndarray:
    """So many words of 64 bits; each mixes the distinct shingles' hashes in its own way."""
    h = hashes[:, None] + np.arange(1, words + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return _majority(h ^ (h >> np.uint64(31)))


def with_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS) -> DataFrame:
    """(doc_id long, fp long): one row per document; fp holds the fingerprint's bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = np.fromiter((fingerprint(t.as_py(), words) for t in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(released(run), "doc_id long, fp long")


def _leaders(members: DataFrame, key: str, node: str, *carried: str) -> DataFrame:
    """(of_key, leader, leader_*): up to four nodes of each key that has several, by two pseudo-random ranks."""
    ranks = [F.struct(F.xxhash64(F.col(node), F.lit(i)).alias("r"), F.col(node).alias("leader"), *[F.col(c).alias(f"leader_{c}") for c in carried]) for i in range(2)]
    picks = [agg(rank).alias(f"l{i}") for i, (agg, rank) in enumerate((a, r) for r in ranks for a in (F.min, F.max))]
    found = members.groupBy(F.col(key).alias("of_key")).agg(*picks, F.count("*").alias("held")).where("held > 1")
    return found.select("of_key", F.explode(F.array_distinct(F.array("l0", "l1", "l2", "l3"))).alias("x")).select("of_key", "x.leader", *[f"x.leader_{c}" for c in carried])


def links(prints: DataFrame, radius: int = RADIUS, n: int | None = None) -> DataFrame:
    """(a, b) of all pairs of distinct fingerprints (column ``fp``, distinct; ``grp``, if there, null or a group) at ``radius`` or fewer differing bits, and not of one group."""
    cut = Cut.planned(prints.count() if n is None else n, radius)
    if "grp" not in prints.columns:
        prints = prints.withColumn("grp", F.lit(None).cast("long"))
    tables = _tables(prints, cut).select("key", F.col("fp").alias("b"), F.col("grp").alias("gb"))
    masks = F.lit([cut.masks(k) for k in range(len(cut.segments))]).cast("array<array<long>>")
    lookups = _tables(prints, cut).select("fp", "grp", "k", "own", F.explode(F.get(masks, F.col("k"))).alias("mask")).withColumn("near", F.col("own").bitwiseXOR(F.col("mask")))
    lookups = lookups.where("near <= own").select(_key(F.col("k"), F.col("near")).alias("key_a"), F.col("fp").alias("a"), F.col("grp").alias("ga"), "k", "mask")

    x = F.col("a").bitwiseXOR(F.col("b"))
    first = F.lit(None).cast("int")
    for k in range(len(cut.segments) - 1, -1, -1):
        first = F.when(F.bit_count(cut.segment(x, k)) <= cut.segments[k][2], k).otherwise(first)
    meets = (F.bit_count(x) <= radius) & (F.col("k") == first) & ((F.col("mask") != 0) | (F.col("a") < F.col("b"))) & ~F.coalesce(F.col("ga") == F.col("gb"), F.lit(False))
    return lookups.join(tables, (F.col("key_a") == F.col("key")) & meets).select("a", "b")


def _key(k: Column, segment: Column) -> Column:
    return segment.bitwiseXOR(F.shiftleft(k.cast("long"), 58))


def _tables(prints: DataFrame, cut: Cut) -> DataFrame:
    """(fp, grp, k, own, key): a row for each segment of each fingerprint."""
    parts = F.array(*[F.struct(F.lit(k).alias("k"), cut.segment(F.col("fp"), k).alias("own")) for k in range(len(cut.segments))])
    return prints.select("fp", "grp", F.explode(parts).alias("s")).select("fp", "grp", "s.k", "s.own", _key(F.col("s.k"), F.col("s.own")).alias("key"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, radius: int = RADIUS) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the smallest id reachable over links of fingerprints."""
    prints, _ = written(with_fingerprints(docs, id_col, text_col, words), "prints")
    nodes, _ = written(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")), "fps")
    n = nodes.count()
    members = _tables(nodes.withColumn("grp", F.lit(None).cast("long")), Cut.planned(n, radius))
    leaders = _leaders(members, "key", "fp")
    close = F.bit_count(F.col("fp").bitwiseXOR(F.col("leader"))) <= radius
    led, _ = written(members.join(leaders, (F.col("key") == F.col("of_key")) & (F.col("fp") != F.col("leader")) & close).select(F.col("fp").alias("a"), F.col("leader").alias("b")), "led")
    stars, _ = written(components(led).select(F.col("node").alias("of"), F.col("root").alias("grp")), "stars")
    grouped = nodes.join(stars, F.col("fp") == F.col("of"), "left").select("fp", "grp")
    roots = components(links(grouped, radius, n).unionByName(stars.select(F.col("of").alias("a"), F.col("grp").alias("b"))))
    placed = nodes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    least = placed.groupBy("root").agg(F.min("rep").alias("component_id")).withColumnRenamed("root", "of")
    classes, _ = written(placed.join(least, F.col("root") == F.col("of")).select(F.col("fp").alias("of_fp"), "component_id"), "classes")
    return prints.join(classes, F.col("fp") == F.col("of_fp")).select("doc_id", "fp", "component_id")


# --- similarity of shingle sets ----------------------------------------------------------------------------------------


def _wide_prints(docs: DataFrame, id_col: str, text_col: str, words: int, plan: Wide) -> DataFrame:
    """(doc_id, h, set_id, shingles, n, row, f0...) of the rows that have an id: the text's XXH64, its set of shingle hashes and the set's fingerprint."""
    names = [f"f{k}" for k in range(plan.words)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                sets = [np.unique(_hashes(t.as_py(), words)) for t in part.column(2)]
                prints = np.array([wide_fingerprint(x, plan.words) for x in sets], np.uint64).reshape(-1, plan.words).view(np.int64)
                ids = pa.array([hashlib.md5(x.tobytes()).hexdigest() for x in sets], pa.string())
                shingles = pa.array([x.view(np.int64) for x in sets], pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), ids, shingles, *(pa.array(np.ascontiguousarray(c)) for c in prints.T)], names=["doc_id", "h", "set_id", "shingles", *names])

    text = F.col(text_col).cast("string")
    rows = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("h"), text.alias("text"))
    rows = rows.mapInArrow(released(run), "doc_id long, h long, set_id string, shingles array<long>, " + ", ".join(f"{n} long" for n in names))
    return rows.withColumn("n", F.size("shingles")).withColumn("row", F.monotonically_increasing_id())


def clusters(nodes: DataFrame, plan: Wide) -> DataFrame:
    """(node, f0..., as many words as ``plan`` has) -> (node, cluster) of all nodes that may have a partner; partners are in one cluster."""
    names = [f"f{k}" for k in range(plan.words)]
    keys = F.array(*[plan.key(names, j) for j in range(plan.count)])
    head = names[:HEAD_WORDS]
    called = lambda x: [F.col(n).alias(f"{x}_{n}") for n in head]
    bits = lambda x, y, of: sum((F.bit_count(F.col(f"{x}_{n}").bitwiseXOR(F.col(f"{y}_{n}"))) for n in of), F.lit(0))

    def near(pairs: DataFrame, allowed: int) -> DataFrame:
        ends = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        side = lambda x: nodes.select(F.col("node").alias(f"n{x}"), *[F.col(n).alias(f"{x}_{n}") for n in names])
        return written(ends.join(side("x"), F.col("a") == F.col("nx")).join(side("y"), (F.col("b") == F.col("ny")) & (bits("x", "y", names) <= allowed)).select("a", "b"), "near")[0]

    soft = SOFT * plan.similarity
    members = nodes.select("node", *head, F.explode(keys).alias("key"))
    leaders = _leaders(members, "key", "node", *head)
    led = members.select("key", F.col("node").alias("a"), *called("a")).join(leaders, (F.col("key") == F.col("of_key")) & (F.col("a") != F.col("leader")) & (bits("a", "leader", head) <= plan.allowed(soft, HEAD_WORDS, 1)))
    stars, _ = written(components(near(led.select("a", F.col("leader").alias("b")), plan.allowed(soft, plan.words, 0))).select(F.col("node").alias("of"), "root"), "stars")

    tables, _ = written(nodes.select("node", *head, keys.alias("keys")).join(stars, F.col("node") == F.col("of"), "left").select("node", *head, F.col("root").alias("star"), F.explode("keys").alias("key")), "segments")
    masks = F.lit([0, *(1 << i for i in range(plan.width))]).cast("array<long>")
    lookups = tables.select("node", *head, "star", "key", F.explode(masks).alias("mask")).withColumn("near", F.col("key").bitwiseXOR(F.col("mask"))).where("near <= key")
    lookups = lookups.select(F.col("node").alias("a"), *called("a"), F.col("star").alias("sa"), F.col("near").alias("key_a"), (F.col("mask") == 0).alias("same"))
    others = tables.select(F.col("node").alias("b"), *called("b"), F.col("star").alias("sb"), "key")
    apart = ~F.coalesce(F.col("sa") == F.col("sb"), F.lit(False)) & (~F.col("same") | (F.col("a") < F.col("b")))
    met = lookups.join(others, (F.col("key_a") == F.col("key")) & apart & (bits("a", "b", head) <= plan.allowed(plan.similarity, HEAD_WORDS, DEVIATIONS)))
    across = near(met.select("a", "b"), plan.allowed(plan.similarity, plan.words, DEVIATIONS))
    return components(across.unionByName(stars.select(F.col("of").alias("a"), F.col("root").alias("b")))).select("node", F.col("root").alias("cluster"))


def common_shingles(sets: list[np.ndarray]) -> np.ndarray:
    """How many numbers any two of the sets (sorted, distinct) have in common, as a matrix; the diagonal is 0."""
    m = len(sets)
    owner = np.repeat(np.arange(m), [len(s) for s in sets])
    flat = np.concatenate(sets) if m else np.empty(0, np.int64)
    by = np.argsort(flat, kind="stable")
    flat, owner = flat[by], owner[by]
    starts = np.flatnonzero(np.concatenate(([True], flat[1:] != flat[:-1]))) if len(flat) else np.empty(0, np.int64)
    held = np.diff(np.append(starts, len(flat)))
    out = np.zeros((m, m), np.float32)
    entry = np.repeat(held, held)
    few = owner[(entry > 1) & (entry <= COMMON)]
    left = np.repeat(held[(held > 1) & (held <= COMMON)], held[(held > 1) & (held <= COMMON)])
    nth = np.arange(len(left)) - np.repeat(np.cumsum(held[(held > 1) & (held <= COMMON)]) - held[(held > 1) & (held <= COMMON)], held[(held > 1) & (held <= COMMON)])
    for d in range(1, COMMON):
        at = np.flatnonzero(nth + d < left)
        if not len(at):
            break
        np.add.at(out, (few[at], few[at + d]), 1)
    many = held > COMMON
    column = np.repeat(np.cumsum(many) - 1, held)[entry > COMMON]
    rows = owner[entry > COMMON]
    for a in range(0, int(many.sum()), 2048):
        here = (column >= a) & (column < a + 2048)
        has = np.zeros((m, 2048), np.float32)
        has[rows[here], column[here] - a] = 1
        out += np.triu(has @ has.T, 1)
    return out + out.T


def _roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least of all that are connected with each of n, by the given links."""
    root = np.arange(n)
    while True:
        after = root.copy()
        least = np.minimum(root[a], root[b])
        np.minimum.at(after, a, least)
        np.minimum.at(after, b, least)
        after = after[after]
        if (after == root).all():
            return root
        root = after


def _met(rows: DataFrame, keys: list[str], similarity: float) -> DataFrame:
    """(node, root) of the nodes that a group of rows (by ``keys``, each as large as two parts) links: node, query, label, shingles.

    Only pairs count of which one is a query and whose labels differ.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in groups(batches, keys):
            node, at = np.unique(group.column("node").to_numpy(), return_index=True)
            if len(node) < 2:
                continue
            asked = np.zeros(len(node), bool)
            np.logical_or.at(asked, np.searchsorted(node, group.column("node").to_numpy()), group.column("query").to_numpy())
            label = group.column("label").to_numpy()[at]
            shingles = group.column("shingles").combine_chunks()
            shingles = shingles.chunk(0) if isinstance(shingles, pa.ChunkedArray) else shingles
            ends, flat = shingles.offsets.to_numpy(), shingles.values.to_numpy()
            sets = [flat[ends[i] : ends[i + 1]] for i in at.tolist()]
            size = np.array([len(s) for s in sets], np.float64)
            alike = common_shingles(sets).astype(np.float64) * (1 + similarity) >= similarity * (size[:, None] + size[None, :]) - 1e-6
            a, b = np.nonzero(np.triu(alike & (asked[:, None] | asked[None, :]) & (label[:, None] != label[None, :]), 1))
            if len(a):
                root = _roots(len(node), a, b)
                linked = np.unique(np.concatenate((a, b)))
                yield pa.RecordBatch.from_pydict({"node": node[linked], "root": node[root[linked]]})

    columns = [*keys, "node", "query", "label", "shingles"]
    return rows.select(*columns).repartition(*keys).sortWithinPartitions(*keys).mapInArrow(released(run), "node long, root long")


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_NODES else df


def verified(prints: DataFrame, placed: DataFrame, similarity: float) -> DataFrame:
    """(a, b): links by which all sets of a cluster that are as similar as asked are connected. ``prints``: (row, n, shingles); ``placed``: (node, cluster)."""
    sizes = prints.select("row", "n").join(_small(placed), F.col("row") == F.col("node")).groupBy("cluster").agg(F.count("*").alias("held"), F.sum("n").alias("total"))
    parts = F.greatest(F.ceil(F.col("held") / PART_SETS), F.ceil(F.col("total") / PART_SHINGLES)).cast("int")
    large, _ = written(sizes.withColumn("parts", parts).where("parts > 1").select(F.col("cluster").alias("of"), "parts"), "large")
    which, _ = written(placed.join(_small(large), F.col("cluster") == F.col("of"), "left").select("node", "cluster", F.coalesce("parts", F.lit(1)).alias("parts")), "which")
    sets = prints.select("row", "n", "shingles").join(_small(which), F.col("row") == F.col("node")).select("cluster", "parts", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int").alias("part"), "node", "n", "shingles")
    sets, _ = written(sets, "sets")
    rank = F.struct(F.xxhash64("node", F.lit(1)).alias("r"), F.col("node").alias("l"))
    chosen = which.where("parts > 1").groupBy("cluster").agg(F.min(rank)["l"].alias("low"), F.max(rank)["l"].alias("high")).select(F.explode(F.array("low", "high")).alias("l"))
    chosen, _ = written(chosen, "leaders")
    sets_led = sets.join(_small(chosen), F.col("node") == F.col("l"), "left")
    everywhere = F.when(F.col("l").isNotNull(), F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array("part"))
    rows = sets_led.select("cluster", F.explode(everywhere).alias("at"), "node", F.lit(True).alias("query"), F.col("node").alias("label"), "shingles")
    inside, _ = written(_met(rows, ["cluster", "at"], similarity), "inside")
    found = inside.select(F.col("node").alias("a"), F.col("root").alias("b"))
    if large.isEmpty():
        return found

    # what a large cluster's parts have left: sets that are not of its largest group meet the sets of all parts
    of_large = which.where("parts > 1")
    roots = components(found.join(of_large.select("node"), F.col("a") == F.col("node"), "left_semi")).withColumnRenamed("node", "of_node")
    labelled, _ = written(of_large.join(roots, F.col("node") == F.col("of_node"), "left").select("node", "cluster", F.coalesce("root", "node").alias("label")), "labelled")
    most = labelled.groupBy("cluster", "label").agg(F.count("*").alias("k")).groupBy("cluster").agg(F.max(F.struct("k", "label"))["label"].alias("most"))
    marked = labelled.join(_small(most.withColumnRenamed("cluster", "of")), F.col("cluster") == F.col("of")).select("node", "label", (F.col("label") != F.col("most")).alias("query"), F.col("cluster").alias("c"))
    marked, _ = written(marked.withColumnRenamed("node", "m"), "marked")
    whole = sets.where("parts > 1").join(_small(marked.drop("c")), F.col("node") == F.col("m"))
    whole, _ = written(whole.select("cluster", "parts", "part", "node", "n", "label", "query", "shingles"), "whole")
    left = whole.where("query").groupBy(F.col("cluster").alias("of")).agg(F.greatest(F.ceil(F.count("*") / PART_SETS), F.ceil(F.sum("n") / PART_SHINGLES)).cast("int").alias("asking"))
    whole = whole.join(_small(written(left, "asking")[0]), F.col("cluster") == F.col("of"))
    queries = whole.where("query").select("cluster", F.pmod(F.xxhash64("node", F.lit(2)), F.col("asking")).cast("int").alias("ask"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("at"), "node", "query", "label", "shingles")
    targets = whole.select("cluster", F.explode(F.sequence(F.lit(0), F.col("asking") - 1)).alias("ask"), F.col("part").alias("at"), "node", F.lit(False).alias("query"), "label", "shingles")
    across, _ = written(_met(queries.unionByName(targets), ["cluster", "ask", "at"], similarity), "across")
    return found.unionByName(across.select(F.col("node").alias("a"), F.col("root").alias("b")))


def _classes(docs: DataFrame, id_col: str, text_col: str, words: int, similarity: float) -> DataFrame:
    """(doc_id, h, first_id, first_h): each row with an id, and the least (id, XXH64 of the text) of its group."""
    plan = Wide.planned(docs.count(), similarity)
    names = [f"f{k}" for k in range(plan.words)]
    prints, _ = written(_wide_prints(docs, id_col, text_col, words, plan), "wide")
    least = F.struct("doc_id", "h")
    nodes, _ = written(prints.groupBy("set_id", *names).agg(F.min("row").alias("node"), F.min(least).alias("least")), "nodes")
    placed, _ = written(clusters(nodes.select("node", *names), plan), "clusters")
    roots = components(verified(prints, placed, similarity)).withColumnRenamed("node", "of_node")
    rooted = nodes.join(roots, F.col("node") == F.col("of_node"), "left").select("set_id", "least", F.coalesce("root", "node").alias("root"))
    smallest = rooted.groupBy("root").agg(F.min("least").alias("first")).withColumnRenamed("root", "of")
    found, _ = written(rooted.join(smallest, F.col("root") == F.col("of")).select(F.col("set_id").alias("of_set"), F.col("first.doc_id").alias("first_id"), F.col("first.h").alias("first_h")), "classes")
    return prints.select("doc_id", "h", "set_id").join(found, F.col("set_id") == F.col("of_set")).select("doc_id", "h", "first_id", "first_h")


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = SIMILAR_WORDS, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, component_id) of rows with an id: groups of texts whose sets of shingles are that similar; candidates come by wide fingerprints."""
    return _classes(docs, id_col, text_col, words, similarity).select("doc_id", F.col("first_id").alias("component_id"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = SIMILAR_WORDS, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs``, all columns, one of each group of similar texts: that of the smallest id, and of the smallest XXH64 of the text among rows of that id.

    Of rows with one id and one text, the first by their columns as JSON stays. Rows with a null id or a null text stay as they are.
    Texts are shuffled only if more rows go than can be broadcast.
    """
    null = F.col(id_col).isNull() | F.col(text_col).isNull()
    texts = docs.where(~null)
    classes, _ = written(_classes(texts, id_col, text_col, words, similarity).groupBy("doc_id", "h").agg(F.max((F.col("doc_id") == F.col("first_id")) & (F.col("h") == F.col("first_h"))).alias("first"), F.count("*").alias("held")), "kept")
    names = [F.col(f"`{c}`") for c in docs.columns]
    others = [F.col(f"`{c}`") for c in docs.columns if c != text_col]
    rows = texts.select(F.col(id_col).cast("long").alias("id"), F.xxhash64(F.col(text_col).cast("string")).alias("hash"), F.struct(*names).alias("row"), F.to_json(F.struct(*others)).alias("as_json"))
    same = (F.col("id") == F.col("doc_id")) & (F.col("hash") == F.col("h"))
    going, _ = written(classes.where("not first or held > 1").select("doc_id", "h"), "going")
    repeated, _ = written(classes.where("first and held > 1").select("doc_id", "h"), "repeated")
    nth = F.row_number().over(Window.partitionBy("id", "hash").orderBy("as_json"))
    stay = rows.join(_small(going), same, "left_anti").select("row.*")
    one = rows.join(_small(repeated), same, "left_semi").withColumn("nth", nth).where("nth = 1").select("row.*")
    return stay.unionByName(one).unionByName(docs.where(null))


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op7: doc_id, fingerprint (16 lowercase hex digits), component_id."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
