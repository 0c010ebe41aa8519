"""Document fingerprints: a homomorphic multiset hash of a text's paragraphs.

A text is the multiset of its paragraphs (lines) and of the clauses they fall into at punctuation. Every element is hashed
to a wide vector: 128 lanes of +1 or -1 and four lanes of 32 bits. The fingerprint is the sum of the vectors, lanes of the
first kind modulo 2^16, of the second modulo 2^32; so it doesn't depend on order, an insertion adds a vector and a deletion
takes it away (``combine``). The 32-bit lanes decide equality. The lanes of +1 and -1 of two texts have a cosine that
estimates how much of their multisets they share, which is the likeness of two fingerprints.

Sums are packed two lanes to a long and are made by one hash aggregation; the lanes of a row's texts come together in the
partition that has the row. Null and empty texts have the fingerprint of the empty multiset, all zero, which is
like itself (1) and like nothing else (0).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

LANES = 128
CLAUSE_END = r"[\n.,;:!?|]+"
#: A document's next one is found within ranges of ids of about so many rows, of which there are MAX_RANGES at most.
RANGE_ROWS = 2_000
MAX_RANGES = 1 << 16

_HALF = 0x0000000100000001


def elements(text: Column) -> Column:
    """The non-empty paragraphs and clauses of a text, as an array."""
    return F.filter(F.concat(F.split(text, "\n"), F.split(text, CLAUSE_END)), lambda x: x != "")


def _sums(element: Column) -> list[Column]:
    of = lambda k: F.when(element.isNotNull(), F.xxhash64(F.lit(k), element))
    hashes = [of(k) for k in range(2)]
    packed = [F.sum(F.shiftrightunsigned(h, j).bitwiseAND(F.lit(_HALF))).alias(f"p{k}_{j}") for k, h in enumerate(hashes) for j in range(32)]
    wide = [F.sum(F.shiftrightunsigned(of(2 + k), 32 * j).bitwiseAND(F.lit(0xFFFFFFFF))).alias(f"w{k}_{j}") for k in range(2) for j in range(2)]
    return [F.count(element).alias("n"), *packed, *wide]


def _vector() -> Column:
    """The sums as 34 longs: 32 of four 16-bit lanes, two of two 32-bit lanes."""
    lane = lambda p, high: (2 * (F.shiftrightunsigned(p, 32) if high else p.bitwiseAND(F.lit(0xFFFFFFFF))) - F.col("n")).bitwiseAND(F.lit(0xFFFF))
    packed = [F.coalesce(F.col(f"p{k}_{j}"), F.lit(0)) for k in range(2) for j in range(32)]
    longs = []
    for i in range(0, 64, 2):
        parts = [lane(packed[i + (m >> 1)], m & 1) for m in range(4)]
        longs.append(_packed(parts, 16))
    for k in range(2):
        longs.append(_packed([F.coalesce(F.col(f"w{k}_{j}"), F.lit(0)).bitwiseAND(F.lit(0xFFFFFFFF)) for j in range(2)], 32))
    return F.array(*longs)


def _packed(parts: list[Column], bits: int) -> Column:
    out = parts[0]
    for m, part in enumerate(parts[1:], 1):
        out = out.bitwiseOR(F.shiftleft(part, bits * m))
    return out


def combine(a: Column, b: Column, sign: int = 1) -> Column:
    """The vector of two multisets put together (sign 1), or of the first without the second (sign -1)."""

    def lanes(i: int, x: Column, y: Column) -> Column:
        bits = 16 if i < 32 else 32
        mask = F.lit((1 << bits) - 1)
        at = lambda v, m: F.shiftrightunsigned(v, bits * m).bitwiseAND(mask)
        return _packed([(at(x, m) + sign * at(y, m)).bitwiseAND(mask) for m in range(64 // bits)], bits)

    return F.array(*[lanes(i, a[i], b[i]) for i in range(34)])


def as_text(vector: Column) -> Column:
    return F.lower(F.concat_ws("", F.transform(vector, lambda x: F.lpad(F.hex(x), 16, "0"))))


def _lanes(vector: Column) -> Column:
    """The 128 small lanes as signed numbers."""
    one = lambda x, m: F.shiftrightunsigned(x, 16 * m).bitwiseAND(F.lit(0xFFFF))
    signed = lambda v: (v - F.when(v >= 0x8000, 0x10000).otherwise(0)).cast("double")
    return F.flatten(F.transform(F.slice(vector, 1, 32), lambda x: F.array(*[signed(one(x, m)) for m in range(4)])))


def likeness(a: Column, b: Column) -> Column:
    """0 to 1; 1 for equal vectors."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    u, v = _lanes(a), _lanes(b)
    size = F.sqrt(dot(u, u) * dot(v, v))
    cosine = F.when(size > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), dot(u, v) / size))).otherwise(0.0)
    return F.when(a == b, 1.0).otherwise(cosine)


def _vectors(texts: DataFrame, keys: list[str], text: str) -> DataFrame:
    rows = texts.select(*keys, F.explode_outer(elements(F.col(text))).alias("element"))
    return rows.groupBy(*keys).agg(*_sums(F.col("element"))).select(*keys, _vector().alias("vector"))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, vector, fingerprint) of each document; rows of one id count as one multiset."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return _vectors(rows, ["doc_id"], "text").select("*", as_text(F.col("vector")).alias("fingerprint"))


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(part, nth, doc_id, text, next): each text with that of the next id; after the last comes the first. Equal ids go by the text's MD5."""
    return _in_ranges(docs, id_col, text_col).where("ghost = 0").select("part", "nth", "doc_id", "text", "next")


def _in_ranges(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(part, ghost, nth, doc_id, text, next): the rows of each range of ids in order, and at its end (ghost 1) the first of the next range.

    Ids are cut into ranges of about RANGE_ROWS rows at quantiles; the first row of a range also goes, as a ghost, to the
    end of the range before. So texts are shuffled once, into windows over one range each. What the driver gets is the ends of the
    ranges, MAX_RANGES at most.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    ids = rows.select("doc_id")
    n = max(1, min(MAX_RANGES, ids.count() // RANGE_ROWS))
    ends = ids.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 20 * n).alias("q")).first()["q"] if n > 1 else None
    ends = sorted(set(ends or ()))
    steps = [1 << k for k in range(len(ends).bit_length() - 1, -1, -1)] if ends else []
    if ends:
        array = F.lit(ends).cast("array<long>")
        step = lambda p, s: F.when((p + s <= len(ends)) & (F.get(array, p + s - 1) <= F.col("doc_id")), p + s).otherwise(p)
        part = F.aggregate(F.lit(steps).cast("array<int>"), F.lit(0), step)
    else:
        part = F.lit(0)
    firsts = {r["part"]: None if r["nulls"] else r["low"] for r in ids.select("doc_id", part.alias("part")).groupBy("part").agg(F.min("doc_id").alias("low"), F.max(F.col("doc_id").isNull()).alias("nulls")).collect()}
    used = sorted(firsts)
    before = {p: used[i - 1] for i, p in enumerate(used)}
    low = F.lit([firsts.get(p) for p in range(len(ends) + 1)]).cast("array<long>")
    prior = F.lit([before.get(p, -1) for p in range(len(ends) + 1)]).cast("array<int>")

    rows = rows.withColumn("at", part)
    own = F.struct(F.col("at").alias("part"), F.lit(0).alias("ghost"))
    ghost = F.struct(F.get(prior, F.col("at")).alias("part"), F.lit(1).alias("ghost"))
    is_first = F.get(low, F.col("at")).eqNullSafe(F.col("doc_id"))
    rows = rows.select("doc_id", "text", F.explode(F.when(is_first, F.array(own, ghost)).otherwise(F.array(own))).alias("to")).select("to.*", "doc_id", "text")
    order = Window.partitionBy("part").orderBy("ghost", F.col("doc_id").asc_nulls_first(), F.md5(F.col("text").cast("binary")))
    return rows.select("part", "ghost", F.row_number().over(order).alias("nth"), "doc_id", "text", F.lead("text").over(order).alias("next"))


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op9: each text, its edited form and the next text, by their fingerprints.

    A text and its edited form are hashed once each; the next text's vector is that of the next row, of which the last row of a range has a ghost.
    """
    rows = _in_ranges(docs, "doc_id", "text")
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next"), F.lit(1), half))
    real = F.col("ghost") == 0
    texts = F.when(real, F.array(F.col("text"), edited)).otherwise(F.array("text"))
    rows = rows.select("part", "nth", "ghost", "doc_id", n.cast("long").alias("n_chars"), F.when(real, F.sha2(edited.cast("binary"), 256)).alias("edited_sha256"), F.posexplode(texts).alias("which", "t"))
    keys = ["part", "nth", "ghost", "doc_id", "n_chars", "edited_sha256", "which"]
    each = _vectors(rows, keys, "t")
    of = lambda k: F.first(F.when(F.col("which") == k, F.col("vector")), ignorenulls=True)
    both = each.groupBy(*keys[:-1]).agg(of(0).alias("a"), of(1).alias("b"))
    both = both.withColumn("c", F.lead("a").over(Window.partitionBy("part").orderBy("nth"))).where(real)
    a, b, c = map(F.col, "abc")
    return both.select("doc_id", "n_chars", "edited_sha256", as_text(a).alias("fingerprint"), as_text(b).alias("edited_fingerprint"), likeness(a, b).alias("near_edited"), likeness(a, c).alias("near_next"))
