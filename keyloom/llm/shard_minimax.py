"""Sharding by a minimax contiguous partition of ordered atomic groups, under the law ``bytes``.

Documents are ordered by the MD5 of their text; an atomic group is what has the same text, its size the bytes of its documents plus 8 for each.
The least capacity for which a greedy pass needs no more than the wanted shards is found by binary search, and the groups are cut there. If even cuts,
each shard taking its share of what is left, keep that same capacity, they are used, so that one huge group
doesn't leave shards empty.

The search runs over ranges of MD5 (atoms), by array expressions over one row: at first 16^DIGITS of them, whatever the table holds. A capacity of one less
fails in some pass over atoms; if every atom that closed a shard in it is a single group, no cut inside an atom could help, and the
capacity is the least for the groups themselves. Otherwise those atoms are cut into 16^FINER finer ones, by one pass over their rows, and the
search runs again; so only atoms at which shards may end are ever refined.

Slots count up within a shard without gaps: documents of a group are spread over 64 parts by their id, offsets
come from the counts of (shard, range, part), and rows are numbered within a part only; so a text with a third of all rows
is numbered in 64 pieces. Null texts count as empty. Repeated rows get slots of their own. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyloom.llm.common import remove, written

SHARDS = 24
#: Hex digits of the MD5 that number an atom, at first and more of them when it is refined.
DIGITS, FINER = 4, 2


def _cuts(n: int) -> str:
    """SQL over a column ``g`` (array of (bin, bytes), by bin): the first bins of all shards but the first."""
    fits = f"""aggregate(g, named_struct('k', 1, 'cur', 0L),
        (s, x) -> IF(s.cur + x.bytes <= (r.lo + r.hi) div 2, named_struct('k', s.k, 'cur', s.cur + x.bytes), named_struct('k', s.k + 1, 'cur', x.bytes)),
        s -> s.k <= {n})"""
    search = f"""aggregate(sequence(1, 62), named_struct('lo', greatest(largest, (total + {n - 1}) div {n}), 'hi', total div {n} + largest + 1L),
        (r, i) -> IF(r.lo >= r.hi, r, IF({fits}, named_struct('lo', r.lo, 'hi', (r.lo + r.hi) div 2), named_struct('lo', (r.lo + r.hi) div 2 + 1, 'hi', r.hi))),
        r -> r.hi)"""
    return f"{search} AS capacity"


def _walk(closes: str, kind: str) -> str:
    """One pass over ``g``; ``fair`` and ``open`` count a bin as the mean shard at most, so that one huge bin doesn't raise what others should take."""
    return f"""aggregate(g, named_struct('cur', 0L, 'fair', 0L, 'open', fair_total, 'worst', 0L, 'cuts', cast(array() as array<{kind}>)),
        (s, x) -> IF(s.cur > 0 AND ({closes}),
            named_struct('cur', x.bytes, 'fair', x.fair, 'open', s.open - s.fair, 'worst', greatest(s.worst, x.bytes), 'cuts', array_append(s.cuts, x.bin)),
            named_struct('cur', s.cur + x.bytes, 'fair', s.fair + x.fair, 'open', s.open, 'worst', greatest(s.worst, s.cur + x.bytes), 'cuts', s.cuts)))"""


def partition(atoms: DataFrame, n_shards: int = SHARDS) -> DataFrame:
    """(bin, bytes, single), one row per atom -> one row (capacity, cuts, closing): the least largest shard, the bins at which shards begin,
    and the bins, not single, that close a shard in the pass that shows that a capacity of one less doesn't do."""
    single = F.col("single") if "single" in atoms.columns else F.lit(True)
    one = atoms.agg(F.array_sort(F.collect_list(F.struct("bin", "bytes", single.alias("single")))).alias("g"), F.coalesce(F.sum("bytes"), F.lit(0)).alias("total"), F.coalesce(F.max("bytes"), F.lit(0)).alias("largest"))
    one = one.selectExpr(f"transform(g, x -> named_struct('bin', x.bin, 'bytes', x.bytes, 'fair', least(x.bytes, total div {n_shards}))) AS g", "map_from_entries(transform(filter(g, x -> NOT x.single), x -> struct(x.bin, true))) AS parted", "total", "largest", _cuts(n_shards))
    one = one.selectExpr("*", "aggregate(g, 0L, (s, x) -> s + x.fair) AS fair_total")
    left = f"({n_shards} - size(s.cuts))"
    kind = dict(atoms.dtypes)["bin"]
    greedy = _walk("s.cur + x.bytes > capacity", kind)
    even = _walk(f"size(s.cuts) < {n_shards - 1} AND (s.cur + x.bytes > capacity OR (2 * s.fair + x.fair) * {left} > 2 * s.open)", kind)
    tight = _walk(f"size(s.cuts) < {n_shards} AND s.cur + x.bytes > capacity - 1", kind)
    huge = "transform(filter(g, x -> x.bytes > capacity - 1), x -> x.bin)"
    one = one.selectExpr("capacity", "parted", f"{even} AS even", f"{greedy} AS greedy", f"{tight} AS tight", f"{huge} AS huge")
    return one.selectExpr("capacity", "IF(even.worst <= capacity, even.cuts, greedy.cuts) AS cuts", "filter(array_union(tight.cuts, huge), x -> parted[x]) AS closing")


def least_cuts(rows: DataFrame, n_shards: int = SHARDS) -> tuple[int, list[str], int]:
    """(capacity, the MD5 prefixes at which shards begin, rounds) for rows (h, size); a group is what shares h."""
    atom = lambda some, digits: some.groupBy(F.substring("h", 1, digits).alias("bin")).agg(F.sum("size").alias("bytes"), (F.min("h") == F.max("h")).alias("single"))
    atoms, path = written(atom(rows, DIGITS), "atoms")
    for round_no in range(1, 1_000):
        found = partition(atoms, n_shards).first()  # n_shards - 1 cuts at most, and as many closing atoms
        if not found["closing"]:
            return found["capacity"], list(found["cuts"]), round_no
        finer = None
        for digits in sorted({len(b) for b in found["closing"]}):
            some = atom(rows.where(F.substring("h", 1, digits).isin([b for b in found["closing"] if len(b) == digits])), digits + FINER)
            finer = some if finer is None else finer.unionByName(some)
        before, (atoms, path) = path, written(atoms.where(~F.col("bin").isin(list(found["closing"]))).unionByName(finer), "atoms")
        remove(rows.sparkSession, before)
    raise AssertionError("atoms of all digits are single groups")


def assign(docs: DataFrame, n_shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot), one row per document."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary")
    rows = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.md5(text).alias("h"))
    part = F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), 1, 2), 16, 10).cast("int")
    rows, _ = written(rows.withColumns({"bin": F.substring("h", 1, DIGITS), "part": F.shiftright(part, 2)}), "sharded")

    _, cuts, _ = least_cuts(rows.select("h", "size"), n_shards)
    shard = F.size(F.filter(F.array(*map(F.lit, cuts)).cast("array<string>"), lambda c: c <= F.col("h")))
    rows = rows.withColumn("shard", shard)
    counts, _ = written(rows.groupBy("shard", "bin", "part").agg(F.count("*").alias("n")), "counts")
    of_shard = Window.partitionBy("shard").orderBy("bin", "part").rowsBetween(Window.unboundedPreceding, -1)
    ahead = counts.select(F.col("shard").alias("s"), F.col("bin").alias("b"), F.col("part").alias("p"), F.coalesce(F.sum("n").over(of_shard), F.lit(0)).alias("ahead"))
    nth = F.row_number().over(Window.partitionBy("shard", "bin", "part").orderBy("h", "doc_id")) - 1
    numbered = rows.withColumn("nth", nth).join(ahead, (F.col("shard") == F.col("s")) & (F.col("bin") == F.col("b")) & (F.col("part") == F.col("p")))
    return numbered.select("doc_id", "size", "text_crc32", "shard", (F.col("ahead") + F.col("nth")).cast("long").alias("slot"))


def digest(docs: DataFrame) -> DataFrame:
    """The rows of query op6; law ``bytes``, so grown_shard is null."""
    rows = assign(docs)
    return rows.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
