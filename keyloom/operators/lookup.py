"""Filters and their lookups: native expressions, joins over slot rows, packed tables, and single keys on the driver.

Keys of the set always get their value. Other keys get NULL but for the filter's error; a NULL key and a key of another type that can't be
cast get NULL. A result that has to be exact for absent keys needs a check against the set (``relational.semi_reduce``).
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyloom.functions.hashing import CHOICE, FIRST, MASK, SECOND, SHARD, derived, digests, key_columns, np_derived, shard_of
from keyloom.functions.packing import gather, pack, to_rows, width_of
from keyloom.operators.kernels import mul_mod
from keyloom.plans.params import DIRECTORY, Spec
from keyloom.plans.scratch import written

#: Tables up to so many bytes are broadcast, if the driver's heap allows; larger ones are joined by shard.
BROADCAST_BYTES = 256 << 20


@dataclass(frozen=True)
class Filter:
    """A built filter: its parameters, the types of its key columns, one row for each shard, and how many keys it has."""

    spec: Spec
    key_types: list[str]
    tables: DataFrame
    n: int
    version: int = 0
    #: The last micro-batch of a feed that is in it.
    batch: int = -1

    def bytes(self) -> int:
        """Bytes of the arrays as rows hold them."""
        cells = sum((F.coalesce(F.size(c), F.lit(0)) for c in ("g", "h", "b")), F.lit(0))
        return 8 * (self.tables.agg(F.sum(F.greatest(cells, F.lit(0)))).first()[0] or 0)

    def blocks(self) -> int:
        """The most blocks that a lookup may try."""
        return self.tables.agg(F.max("n_blocks")).first()[0] or 1 if self.spec.kind == "sparse" else 1

    def get(self, *key) -> int | None:
        """The value of one key: reads the table's row of the key's shard."""
        spark = self.tables.sparkSession
        names = [f"k{i}" for i in range(len(key))]
        probe = spark.createDataFrame([tuple(key)], ", ".join(f"{n} {t}" for n, t in zip(names, self.key_types)))
        d0, d1 = digests(names, self.key_types, self.spec.family)
        shard = probe.select(d0.alias("d0"), d1.alias("d1")).select(shard_of(self.spec.shards, self.spec.seed, self.spec.family)).first()[0]
        return lookup(probe, replace(self, tables=self.tables.where(F.col("shard") == shard)), names, strategy="broadcast").first()["value"]

    def with_tables(self, tables: DataFrame) -> Filter:
        return replace(self, tables=tables, version=self.version + 1)


#: Blocks of a sparse filter whose look-up is written out, a projection each; more than those are tried in a loop, for which every row takes a copy of its shard's slots.
INLINE_BLOCKS = 64
#: Columns of the table's side of a lookup, and names that a lookup gives to its own.
SIDE = ("shard", "n_slots", "seed", "n_blocks", "extra", "p", "g", "h", "b")
#: Rows with a NULL key are spread over so many keys that no shard has.
NULL_SALTS = 4096


def _apart(df: DataFrame) -> tuple[DataFrame, list[Column]]:
    """``df`` under names that no lookup uses, and the columns that give its own back. Changes nothing unless names clash."""
    own = {"d0", "d1", *(f"_{c}" for c in ("shard", "known", "salt", "above", "block")), *(f"_t_{c}" for c in SIDE), *(f"_b_{c}" for c in DIRECTORY)}
    if not own & set(df.columns):
        return df, [F.col(f"`{c}`") for c in df.columns]
    names = [f"_own_{i}" for i in range(len(df.columns))]
    return df.toDF(*names), [F.col(n).alias(c) for n, c in zip(names, df.columns)]


def _probe(df: DataFrame, filter: Filter, key) -> DataFrame:
    """``df`` with d0, d1, whether its key is _known (not NULL), and its _shard; NULL keys get negative numbers, so that they are spread and meet nothing."""
    spec = filter.spec
    d0, d1 = digests(key, filter.key_types, spec.family)
    known = F.lit(True)
    for c, kind in zip(key_columns(key), filter.key_types):
        known = known & F.col(c).cast(kind).isNotNull()
    probe = df.withColumns({"d0": d0, "d1": d1, "_known": known})
    spread = F.lit(-1) if df.isStreaming else -1 - F.pmod(F.monotonically_increasing_id(), F.lit(NULL_SALTS)).cast("int")  # streams only meet broadcast tables
    return probe.withColumn("_shard", F.when(F.col("_known"), shard_of(spec.shards, spec.seed, spec.family)).otherwise(spread))


def _renamed(df: DataFrame, key) -> tuple[DataFrame, list[Column], list[str]]:
    apart, back = _apart(df)
    names = key_columns(key)
    return apart, back, names if apart is df else [apart.columns[df.columns.index(c)] for c in names]


def broadcast_limit(spark) -> int:
    """Bytes of a table that is broadcast unasked: BROADCAST_BYTES, and a 16th of the driver's heap at most. The driver holds the table as collected, as built (in pages that double) and in blocks."""
    return min(BROADCAST_BYTES, spark.sparkContext._jvm.java.lang.Runtime.getRuntime().maxMemory() // 16)


def lookup(df: DataFrame, filter: Filter, key, out: str = "value", strategy: str = "auto") -> DataFrame:
    """``df`` with the looked-up value as a nullable column ``out``. strategy: auto, broadcast (refused above BROADCAST_BYTES), shuffle_hash or merge."""
    if strategy in ("auto", "broadcast"):
        small = filter.bytes() <= (BROADCAST_BYTES if strategy == "broadcast" else broadcast_limit(filter.tables.sparkSession))
        if strategy == "broadcast" and not small:
            raise ValueError(f"the filter has more than {BROADCAST_BYTES} bytes; shuffle_hash or merge join it by shard")
        strategy = "broadcast" if small else "shuffle_hash"
    if strategy not in ("broadcast", "shuffle_hash", "merge"):
        raise ValueError(strategy)
    rows, back, names = _renamed(df, key)
    probe = _probe(rows, filter, names)
    side = filter.tables.select(*[F.col(c).alias(f"_t_{c}") for c in SIDE])
    side = F.broadcast(side) if strategy == "broadcast" else side.hint(strategy)
    joined = probe.join(side, F.col("_shard") == F.col("_t_shard"), "left")
    if filter.spec.buckets:
        joined = joined.withColumns(_directory(filter.spec))
    if filter.spec.kind == "sparse":
        joined, value = _tried(joined, filter.spec, filter.blocks())
    else:
        value = evaluate(filter.spec)
    return joined.select(*back, F.when(F.col("_known"), value).alias(out))


def _directory(spec: Spec) -> dict[str, Column]:
    """What a shard's directory says of the key's bucket: where its slots are, its own prime, blocks and seed."""
    bucket = F.pmod(derived(F.lit(spec.seed).cast("long"), SHARD, spec.family), F.lit(spec.shards * spec.buckets).cast("long"))
    at = F.floor(bucket / F.lit(spec.shards)).cast("long") if spec.shards > 1 else bucket
    entry = F.slice("_t_h", (at * len(DIRECTORY) + 1).cast("int"), F.lit(len(DIRECTORY)))
    return {f"_b_{c}": F.get(entry, i) for i, c in enumerate(DIRECTORY)}


def bucket_of(spec: Spec, d0: np.ndarray, d1: np.ndarray) -> np.ndarray:
    """The bucket of each key; bucket // shards is its place in its shard, bucket % shards."""
    return np_derived(spec.seed, SHARD, d0, d1) % (spec.shards * spec.buckets)


def _tried(joined: DataFrame, spec: Spec, blocks: int) -> tuple[DataFrame, Column]:
    """The lookup of a sparse filter: ``joined`` with _block, the residue of the first block to answer or of the last, and the value as a column.

    _above has the residue's bits beyond those of a value; a residue without any is the answer, and no later block is tried. Each projection needs
    the residue twice, for _block and for _above: so Spark gives it a method of its own. In one method with the others it would not be compiled by a JVM.
    """
    first, n, p, held, seed = (F.col(f"_b_{c}") for c in DIRECTORY) if spec.buckets else (F.lit(0).cast("long"), F.col("_t_n_slots"), F.col("_t_p"), F.col("_t_n_blocks").cast("long"), F.col("_t_seed"))

    def block(j: Column) -> Column:
        total = F.pmod(derived(seed, MASK, spec.family), p)
        for t in range(spec.s):
            role = (j * (2 * spec.s) + (CHOICE + 2 * t)).cast("long")
            cell = F.get("_t_g", (first + F.pmod(derived(seed, role, spec.family), n)).cast("int"))
            total = F.pmod(total + _product(1 + F.pmod(derived(seed, role + 1, spec.family), p - 1), cell, p, spec.p_bits), p)
        return total

    residue, above = F.col("_block"), F.col("_above")
    joined = joined.withColumns({"_block": F.lit(None).cast("long"), "_above": F.lit(1).cast("long")})
    for j in range(min(blocks, INLINE_BLOCKS)):
        tried = F.when((above != 0) & (F.lit(j) < held), block(F.lit(j))).otherwise(residue)
        joined = joined.withColumns({"_block": tried, "_above": F.coalesce(F.shiftright(tried, spec.k), F.lit(1).cast("long"))})
    found = F.when((above == 0) & residue.isNotNull(), residue)  # a residue named once would be put in here, and computed twice
    if blocks > INLINE_BLOCKS:
        limit = F.lit(1 << spec.k)
        asked = lambda j: F.when((j < held) & (block(j) < limit), block(j))
        rest = F.aggregate(F.sequence(F.lit(INLINE_BLOCKS), F.lit(blocks - 1)), F.lit(None).cast("long"), lambda before, j: F.coalesce(before, asked(j)))
        return joined, F.when(above != 0, rest).otherwise(found)
    return joined, found


def evaluate(spec: Spec) -> Column:
    """The lookup as one expression over d0, d1 and the columns _t_* of the shard's row; sparse filters have ``_tried``."""
    seed, n = F.col("_t_seed"), F.col("_t_n_slots")
    g = lambda at: F.get("_t_g", at.cast("int"))
    h = lambda at: F.get("_t_h", at.cast("int"))
    hash_of = lambda role: derived(seed, role, spec.family)
    in_range = lambda x: F.when(x < F.lit(1 << spec.k), x)
    if spec.kind in ("acyclic", "mutable", "af_raw"):
        u = F.pmod(hash_of(FIRST), n)
        v = F.pmod(u + 1 + F.pmod(hash_of(SECOND), n - 1), n) if spec.distinct else F.pmod(hash_of(SECOND), n)
        m = F.lit(spec.modulus).cast("long")
        if spec.kind == "af_raw":
            return F.pmod(g(u) + g(v), m)
        return in_range(F.pmod(g(u) + g(v) + F.pmod(hash_of(MASK), m), m))
    if spec.kind == "peeled":
        ends = [F.floor(n * j / spec.r) if j else F.lit(0).cast("long") for j in range(spec.r + 1)]
        m = F.lit(spec.modulus).cast("long")
        x = F.pmod(hash_of(MASK), m)
        for j in range(spec.r):
            x = F.pmod(x + g(ends[j] + F.pmod(hash_of(CHOICE + j), ends[j + 1] - ends[j])), m)
        return in_range(x)
    if spec.kind == "matched":
        ends = [F.floor(n * j / spec.r) if j else F.lit(0).cast("long") for j in range(spec.r + 1)]
        at = [ends[j] + F.pmod(hash_of(CHOICE + j), ends[j + 1] - ends[j]) for j in range(spec.r)]
        which = F.pmod(hash_of(MASK), F.lit(1 << spec.q_bits))
        for a in at:
            which = which.bitwiseXOR(g(a))
        value = F.lit(None).cast("long")
        for j, a in enumerate(at):
            value = F.when(which == j, h(a)).otherwise(value)
        return value
    if spec.kind == "xor":
        first, n, seed = (F.col(f"_b_{c}") for c in ("first", "slots", "seed"))
        x = F.pmod(derived(seed, MASK, spec.family), F.lit(spec.modulus))
        for t in range(spec.s):
            x = x.bitwiseXOR(g(first + F.pmod(derived(seed, CHOICE + t, spec.family), n)))
        return in_range(x)
    if spec.kind == "membership":
        return F.when(_might_contain(spec, n), F.lit(1).cast("long"))
    home = F.pmod(hash_of(1), n)
    at = F.array_position(F.slice("_t_g", (home + 1).cast("int"), F.col("_t_extra").cast("int")), F.col("d0"))
    found = h(home + at - 1)
    found = F.when((at > 0) & (found >= 0), found)
    if spec.kind == "dict_membership":
        return F.when(_might_contain(spec, F.size("_t_b") * F.lit(64)), found)
    return found


def _product(a: Column, b: Column, p: Column, p_bits: int) -> Column:
    """A product of residues; of those above 31 bits in decimals, which hold the 122 bits of a product."""
    if p_bits <= 31:
        return F.pmod(a * b, p)
    wide = lambda x: x.cast("decimal(19,0)")
    return (wide(a) * wide(b) % wide(p)).cast("long")


def _might_contain(spec: Spec, n_bits: Column) -> Column:
    seed = F.xxhash64(F.lit(spec.seed).cast("long"), F.col("_t_shard").cast("long"), F.lit(0).cast("long"))
    n_bits = n_bits.cast("long")
    first, step = F.pmod(derived(seed, 1), n_bits), F.pmod(derived(seed, 2), n_bits)
    held = F.lit(True)
    for j in range(spec.hashes):
        at = F.pmod(first + j * step, n_bits)
        held = held & (F.getbit(F.get("_t_b", F.shiftright(at, 6).cast("int")), at.bitwiseAND(F.lit(63)).cast("int")) == 1)
    return held


def np_evaluate(spec: Spec, row: dict, d0: np.ndarray, d1: np.ndarray, tally: dict[str, int] | None = None) -> np.ndarray:
    """The same lookup in NumPy over one shard's row; -1 is NULL. Kernels verify their members with it. ``tally`` counts the hashes and reads that it takes."""
    seed, n = row.get("seed"), row.get("n_slots")
    array = lambda name: np.asarray(row[name], np.int64) if row.get(name) is not None else None
    g, h = array("g"), array("h")
    keys = np.arange(len(d0))

    def counted(what: str, k: int) -> None:
        if tally is not None:
            tally[what] = tally.get(what, 0) + k

    def of(role: int, some: np.ndarray = keys, seed=seed) -> np.ndarray:
        counted("hashes", len(some))
        return np_derived(seed if np.ndim(seed) == 0 else seed[some], role, d0[some], d1[some], spec.family)

    def read(cells: np.ndarray, at: np.ndarray) -> np.ndarray:
        counted("reads", at.size)
        return cells[at]

    limit = 1 << spec.k
    if spec.shards > 1 or spec.buckets:
        counted("hashes", len(d0))  # that which tells the shard or bucket
    if spec.kind in ("acyclic", "mutable", "af_raw"):
        u = of(FIRST) % n
        v = (u + 1 + of(SECOND) % (n - 1)) % n if spec.distinct else of(SECOND) % n
        x = (read(g, u) + read(g, v) + (0 if spec.kind == "af_raw" else of(MASK) % spec.modulus)) % spec.modulus
        return np.where(x < limit, x, -1)
    if spec.kind == "peeled":
        ends = [n * j // spec.r for j in range(spec.r + 1)]
        x = of(MASK) % spec.modulus
        for j in range(spec.r):
            x = (x + read(g, ends[j] + of(CHOICE + j) % (ends[j + 1] - ends[j]))) % spec.modulus
        return np.where(x < limit, x, -1)
    if spec.kind == "matched":
        ends = [n * j // spec.r for j in range(spec.r + 1)]
        at = np.stack([ends[j] + of(CHOICE + j) % (ends[j + 1] - ends[j]) for j in range(spec.r)])
        which = np.bitwise_xor.reduce(read(g, at), axis=0) ^ (of(MASK) % (1 << spec.q_bits))
        ok = np.flatnonzero(which < spec.r)
        out = np.full(len(d0), -1)
        out[ok] = read(h, at[which[ok], ok])
        return out
    if spec.kind == "sparse":
        if spec.buckets:
            first, width, p, held, seeds = h.reshape(-1, len(DIRECTORY))[bucket_of(spec, d0, d1) // spec.shards].T
        else:
            first, width, p, held = (np.full(len(d0), x) for x in (0, n, row["p"], row["n_blocks"]))
            seeds = np.full(len(d0), seed)
        out, mask = np.full(len(d0), -1), of(MASK, seed=seeds) % p
        for j in range(int(held.max(initial=0))):
            left = np.flatnonzero((out < 0) & (j < held))
            x, prime = mask[left], p[left]
            for t in range(spec.s):
                role = CHOICE + 2 * (j * spec.s + t)
                at = first[left] + of(role, left, seeds) % width[left]
                x = (x + mul_mod(1 + of(role + 1, left, seeds) % (prime - 1), read(g, at), prime)) % prime if len(left) else x
            out[left] = np.where(x < limit, x, -1)
        return out
    if spec.kind == "xor":
        first, width, _, _, seeds = h.reshape(-1, len(DIRECTORY))[bucket_of(spec, d0, d1) // spec.shards].T
        x = of(MASK, seed=seeds) % spec.modulus
        for t in range(spec.s):
            x = x ^ read(g, first + of(CHOICE + t, seed=seeds) % width)
        return np.where(x < limit, x, -1)
    home, out = of(1) % n, np.full(len(d0), -1)
    for step in range(row["extra"]):
        left = np.flatnonzero(out < 0)
        at = np.minimum(home[left] + step, len(g) - 1)
        out[left] = np.where((read(g, at) == d0[left]) & (h[at] >= 0), h[at], -1)
    return out


def lookup_relational(df: DataFrame, filter: Filter, key, out: str = "value") -> DataFrame:
    """The lookup of an acyclic filter as two equi-joins with rows (shard, slot, g)."""
    spec = filter.spec
    if spec.kind not in ("acyclic", "mutable"):
        raise ValueError(f"{spec.kind}: only acyclic filters have two slots for each key")
    d0, d1 = digests(key, filter.key_types, spec.family)
    keep = [F.col(c).alias(f"_k_{c}") for c in df.columns]
    probe = df.select(*keep, d0.alias("d0"), d1.alias("d1")).withColumn("_s", shard_of(spec.shards, spec.seed, spec.family))
    heads = filter.tables.select(F.col("shard").alias("_h"), F.col("n_slots").alias("_n"), F.col("seed").alias("_seed"))
    probe = probe.join(heads, F.col("_s") == F.col("_h"), "left")
    u = F.pmod(derived(F.col("_seed"), FIRST, spec.family), F.col("_n"))
    second = derived(F.col("_seed"), SECOND, spec.family)
    v = F.pmod(u + 1 + F.pmod(second, F.col("_n") - 1), F.col("_n")) if spec.distinct else F.pmod(second, F.col("_n"))
    m = F.lit(spec.modulus).cast("long")
    probe = probe.withColumns({"_u": u, "_v": v, "_m": F.pmod(derived(F.col("_seed"), MASK, spec.family), m)})
    cells = to_rows(filter.tables)
    at = lambda name: cells.select(F.col("shard").alias(f"{name}s"), F.col("slot").cast("long").alias(f"{name}t"), F.col("g").alias(f"{name}g"))
    probe = probe.join(at("a"), (F.col("_s") == F.col("as")) & (F.col("_u") == F.col("at")), "left").join(at("b"), (F.col("_s") == F.col("bs")) & (F.col("_v") == F.col("bt")), "left")
    x = F.pmod(F.col("ag") + F.col("bg") + F.col("_m"), m)
    return probe.select(*[F.col(f"_k_{c}").alias(c) for c in df.columns], F.when(x < (1 << spec.k), x).alias(out))


def packed(filter: Filter) -> DataFrame:
    """(shard, n_slots, seed, g binary): slots at their exact width, as they are stored."""
    width = width_of(filter.spec.modulus)

    def run(batches):
        for batch in batches:
            data = [pack(np.asarray(x, np.int64), width) for x in batch.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(data, pa.binary())], names=["shard", "n_slots", "seed", "g"])

    return filter.tables.select("shard", "n_slots", "seed", "g").mapInArrow(run, "shard int, n_slots long, seed long, g binary")


#: Probes of one shard in a task of a packed lookup.
PACKED_PROBES = 4_000_000


def lookup_packed(df: DataFrame, filter: Filter, key, out: str = "value") -> DataFrame:
    """``df`` with the value as column ``out``, by shard against packed slots.

    Shards and probes meet in sorted rows, a shard's bytes before its probes, so that a task holds one shard and one batch. A shard with more than
    PACKED_PROBES probes is dealt over several tasks, each of which gets its bytes.
    """
    spec = filter.spec
    if spec.kind not in ("acyclic", "mutable"):
        raise ValueError(f"{spec.kind} has no packed form")
    width = width_of(spec.modulus)
    rows, back, names = _renamed(df, key)
    probe = _probe(rows, filter, names)
    held = probe.where("_known").groupBy("_shard").count().where(F.col("count") > PACKED_PROBES)
    parts = held.select(F.col("_shard").alias("_hot"), F.ceil(F.col("count") / PACKED_PROBES).cast("int").alias("_parts"))
    parts = F.broadcast(written(parts, "parts")[0])  # at most a row for each shard of more than PACKED_PROBES probes
    n_parts = F.coalesce("_parts", F.lit(1))
    probe = probe.join(parts, F.col("_shard") == F.col("_hot"), "left").withColumn("_salt", F.pmod(F.monotonically_increasing_id(), n_parts).cast("int"))
    sides = packed(filter).join(parts, F.col("shard") == F.col("_hot"), "left").select(F.col("shard").alias("_shard"), F.explode(F.sequence(F.lit(0), n_parts - 1)).alias("_salt"), F.lit(0).alias("_kind"), "n_slots", "seed", "g")
    own = F.struct(*[F.col(f"`{c}`") for c in rows.columns])
    asked = probe.select("_shard", "_salt", F.lit(1).alias("_kind"), "d0", "d1", "_known", own.alias("_row"))
    both = sides.unionByName(asked, allowMissingColumns=True).select("_shard", "_salt", "_kind", "n_slots", "seed", "g", "d0", "d1", "_known", "_row")

    def run(batches):
        have = slots = seed = data = None
        for batch in batches:
            shards, kinds = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 2))
            cuts = np.flatnonzero(np.concatenate(([True], (shards[1:] != shards[:-1]) | (kinds[1:] != kinds[:-1]) | (kinds[1:] == 0), [True])))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                if kinds[a] == 0:
                    have, slots, seed, data = int(shards[a]), *(batch.column(i)[a].as_py() for i in (3, 4, 5))
                    continue
                part = batch.slice(a, b - a)
                if int(shards[a]) != have:
                    value = pa.nulls(b - a, pa.int64())
                else:
                    x, y = (part.column(i).to_numpy(zero_copy_only=False) for i in (6, 7))
                    u = np_derived(seed, FIRST, x, y, spec.family) % slots
                    second = np_derived(seed, SECOND, x, y, spec.family)
                    v = (u + 1 + second % (slots - 1)) % slots if spec.distinct else second % slots
                    found = (gather(data, width, u) + gather(data, width, v) + np_derived(seed, MASK, x, y, spec.family) % spec.modulus) % spec.modulus
                    value = pa.array(found, pa.int64(), mask=found >= 1 << spec.k)
                yield pa.RecordBatch.from_arrays([part.column(9), value], names=["_row", "_value"])

    meet = both.repartition("_shard", "_salt").sortWithinPartitions("_shard", "_salt", "_kind")
    found = meet.mapInArrow(run, f"_row {both.schema['_row'].dataType.simpleString()}, _value long")
    return found.select("_row.*", F.col("_value").alias("_value")).select(*back, F.col("_value").alias(out))
