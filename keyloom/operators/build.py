"""Builders: one row of ``tables`` for each shard, made by one shuffle and one Arrow kernel.

All of them take a DataFrame, its key column or columns and its value column, and return a ``Filter``. Keys are unique and not null, and
values are k-bit numbers: a NULL key, a value out of range, a repeated key and two values for one key raise an error, wherever they turn up.
Retries stay inside a shard's task, so a bad draw never holds up other shards.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.functions.hashing import CHOICE, FAMILIES, MASK, check_key_types, digests, key_columns, next_seed, np_derived, shard_of
from keyloom.functions.numtheory import choose_primes
from keyloom.operators import kernels as K
from keyloom.operators.lookup import Filter, bucket_of, np_evaluate
from keyloom.plans.params import Spec, acyclic_probability, bucket_tail, check_c, check_k, component_bound, modulus_for, shards_for
from keyloom.plans.scratch import written

TABLES = pa.schema([("shard", pa.int32()), ("n_keys", pa.int64()), ("n_slots", pa.int64()), ("seed", pa.int64()), ("attempts", pa.int32()), ("n_blocks", pa.int32()), ("tries", pa.int64()), ("max_component", pa.int32()), ("extra", pa.int64()), ("first_block", pa.int64()), ("p", pa.int64()), ("seconds", pa.float64()), ("g", pa.list_(pa.int64())), ("h", pa.list_(pa.int64())), ("b", pa.list_(pa.int64()))])
TABLES_SQL = "shard int, n_keys long, n_slots long, seed long, attempts int, n_blocks int, tries long, max_component int, extra long, first_block long, p long, seconds double, g array<long>, h array<long>, b array<long>"


def _digested(df: DataFrame, key, value: str | None, kinds: list[str], spec: Spec) -> DataFrame:
    """(shard, d0, d1, value): 28 bytes a key. NULL keys and values out of range raise here, in the scan's own stage."""
    names = key_columns(key)
    null = F.lit(False)
    for n in names:
        null = null | F.col(n).isNull()
    v = (F.col(value) if value else F.lit(0)).cast("long")
    # d0 is NULL for a NULL key and the kernel refuses it; raising in the expression would keep the scan from being pruned
    d0, d1 = digests(key, kinds, spec.family)
    rows = df.select(F.when(~null, d0).alias("d0"), d1.alias("d1"), v.alias("value"))
    return rows.select(F.coalesce(shard_of(spec.shards, spec.seed, spec.family), F.lit(0)).alias("shard"), "d0", "d1", "value")


def _build(df: DataFrame, key, value: str | None, spec: Spec, n: int) -> Filter:
    kinds = check_key_types(df, key)

    def run(table: pa.Table) -> pa.Table:
        return build_table(spec, table)

    tables = _digested(df, key, value, kinds, spec).groupBy("shard").applyInArrow(run, TABLES_SQL)
    return Filter(spec, kinds, written(tables, "filter")[0], n)


def build_table(spec: Spec, table: pa.Table) -> pa.Table:
    """The kernel of one shard: (shard, d0, d1, value) -> its row of tables."""
    if table.column("d0").null_count:
        raise K.BuildError("a key is NULL")
    if table.column("value").null_count:
        raise K.BuildError("a value is NULL")
    shard = table.column("shard")[0].as_py()
    d0, d1, value = (table.column(c).to_numpy() for c in ("d0", "d1", "value"))
    order = np.lexsort((d1, d0))  # the same bytes whatever order the shuffle gave
    d0, d1, value = d0[order], d1[order], value[order]
    if len(value) and (value.min() < 0 or int(value.max()) >> spec.k):
        raise K.BuildError(f"a value doesn't fit in {spec.k} bits")
    K.check_distinct(d0, d1, value)
    start = time.thread_time()
    row = KERNELS[spec.kind](spec, shard, d0, d1, value)
    row = {"shard": shard, "n_keys": len(d0), "n_blocks": 1, "tries": len(d0), "max_component": 0, "extra": 0, "first_block": 0, "p": 0, "h": None, "b": None} | row | {"seconds": time.thread_time() - start}
    if spec.kind not in ("membership", "af_raw") and not (np_evaluate(spec, row, d0, d1) == value).all():
        raise AssertionError("a member is not looked up as it was stored")
    return pa.table({f.name: pa.array([row[f.name]], f.type) for f in TABLES}, schema=TABLES)


# --- kernels -----------------------------------------------------------------------------------------------------------


def _attempts(spec: Spec, shard: int, n: int, slots: int):
    for attempt in range(1, spec.max_attempts + 1):
        yield attempt, next_seed(spec.seed, shard, attempt)
    raise K.BuildError(f"shard {shard}: {spec.max_attempts} seeds were not enough for {n} keys in {slots} slots")


def _acyclic(spec: Spec, shard: int, d0, d1, value) -> dict:
    slots = max(2, math.ceil(spec.c * len(d0)))
    for attempt, seed in _attempts(spec, shard, len(d0), slots):
        u, v = K.endpoints(d0, d1, seed, slots, spec.distinct, spec.family)
        if (peeled := K.is_forest(u, v, slots)) is None:
            continue
        mask = 0 if spec.kind == "af_raw" else K.masks(d0, d1, seed, spec.modulus, spec.family)
        rhs = (value - mask) % spec.modulus
        if not spec.canonical:
            return {"n_slots": slots, "seed": seed, "attempts": attempt, "g": K.settle_forest(peeled, u, v, rhs, slots, spec.modulus)}
        forest = K.solve_forest(peeled, u, v, rhs, slots, spec.modulus)
        largest = int(forest.sizes.max())
        if spec.kind == "mutable" and largest > spec.component_cap:
            continue
        trees = int((forest.sizes > 1).sum())
        return {"n_slots": slots, "seed": seed, "attempts": attempt, "max_component": largest, "extra": len(d0) + trees, "g": forest.g, "h": forest.component if spec.kind == "mutable" else None}


def _matched(spec: Spec, shard: int, d0, d1, value) -> dict:
    slots = max(2 * spec.r, math.ceil(spec.c * len(d0)))
    for attempt, seed in _attempts(spec, shard, len(d0), slots):
        at = K.positions(d0, d1, seed, slots, spec.r)
        peeled = (K.peel if spec.matching == "peel" else K.match_by_sorting)(at, slots)
        if peeled.done:
            g, h = K.fill_two_tables(peeled, at, value, K.masks(d0, d1, seed, 1 << spec.q_bits), slots)
            return {"n_slots": slots, "seed": seed, "attempts": attempt, "g": g, "h": h}


def _peeled(spec: Spec, shard: int, d0, d1, value) -> dict:
    slots = max(3 * spec.r, math.ceil(spec.c * len(d0)) + 8)
    for attempt, seed in _attempts(spec, shard, len(d0), slots):
        at = K.positions(d0, d1, seed, slots, spec.r)
        peeled = K.peel(at, slots)
        if peeled.done:
            rhs = (value - K.masks(d0, d1, seed, spec.modulus)) % spec.modulus
            return {"n_slots": slots, "seed": seed, "attempts": attempt, "g": K.solve_peeled(peeled, at, rhs, slots, spec.modulus)}


def sparse_row(d0, d1, seed: int, block: int, s: int, q: int, p: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and coefficients of each key in one block; shape (s, n)."""
    roles = [CHOICE + 2 * (block * s + t) for t in range(s)]
    return np.stack([np_derived(seed, r, d0, d1) % q for r in roles]), np.stack([1 + np_derived(seed, r + 1, d0, d1) % (p - 1) for r in roles])


def _sparse(spec: Spec, shard: int, d0, d1, value) -> dict:
    """One system, or the buckets of a shard. ``extra`` counts the members that an earlier block answered wrongly in systems that were then rebuilt."""
    if spec.buckets:
        return _sparse_buckets(spec, shard, d0, d1, value)
    n = len(d0)
    primes = choose_primes(n, spec.eps, spec.p_bits, spec.seed, "direct", spec.field)
    q, p = primes.q, primes.p
    wrong_before = 0
    for attempt, seed in _attempts(spec, shard, n, q):
        mask = K.masks(d0, d1, seed, p)
        rows = K.Echelon(q, p)
        blocks: list[tuple[np.ndarray, np.ndarray]] = []
        used = np.zeros(n, np.int64)
        for i in range(n):
            for j in range(spec.max_blocks):
                if j == len(blocks):
                    blocks.append(sparse_row(d0, d1, seed, j, spec.s, q, p))
                at, by = blocks[j]
                row = np.zeros(q + 1, np.int64)
                for t in range(spec.s):  # positions may coincide: their coefficients add up
                    row[at[t, i]] = (row[at[t, i]] + by[t, i]) % p
                row[-1] = (value[i] - mask[i]) % p
                if rows.try_add(row):
                    used[i] = j
                    break
            else:
                break
        else:
            out = {"n_slots": q, "seed": seed, "attempts": attempt, "n_blocks": int(used.max(initial=0)) + 1, "tries": int((used + 1).sum()), "first_block": int((used == 0).sum()), "p": p, "g": rows.solution()}
            wrong = int((np_evaluate(spec, out, d0, d1) != value).sum())
            if not wrong:
                return out | {"extra": wrong_before}
            wrong_before += wrong


def _sparse_buckets(spec: Spec, shard: int, d0, d1, value) -> dict:
    """The systems of all buckets of a shard, eliminated side by side: their slots one after the other in ``g``, their directory in ``h``."""
    local = bucket_of(spec, d0, d1) // spec.shards
    sizes = np.bincount(local, minlength=spec.buckets)
    primes = [choose_primes(max(1, int(n)), spec.eps, spec.p_bits, spec.seed, "direct", spec.field) for n in sizes]
    q, p = np.array([x.q for x in primes], np.int64), np.array([x.p for x in primes], np.int64)
    order = np.argsort(local, kind="stable")
    starts = np.cumsum(sizes) - sizes
    solved: list[np.ndarray | None] = [None] * spec.buckets
    seeds, blocks, tries = np.zeros(spec.buckets, np.int64), np.ones(spec.buckets, np.int64), np.zeros(spec.buckets, np.int64)
    first_block = wrong_before = attempts = 0
    left = np.arange(spec.buckets)
    for attempt in range(1, spec.max_attempts + 1):
        attempts = attempt
        for b in left.tolist():
            seeds[b] = next_seed(spec.seed, shard, b, attempt)
        keys = order[np.isin(local[order], left)]
        of = np.searchsorted(left, local[keys])
        mine = {"seed": seeds[local[keys]], "q": q[local[keys]], "p": p[local[keys]]}
        rhs = (value[keys] - np_derived(mine["seed"], MASK, d0[keys], d1[keys]) % mine["p"]) % mine["p"]
        system = K.Echelons(q[left], p[left], max(1, int(sizes[left].max(initial=1))))
        nth = np.arange(len(keys)) - np.repeat(np.cumsum(sizes[left]) - sizes[left], sizes[left])
        used = np.full(len(keys), -1)
        for i in range(int(sizes[left].max(initial=0))):
            now = np.flatnonzero(nth == i)
            for j in range(spec.max_blocks):
                rows = np.zeros((len(now), system.width + 1), np.int64)
                seed, width, prime = mine["seed"][now], mine["q"][now], mine["p"][now]
                for t in range(spec.s):
                    role = CHOICE + 2 * (j * spec.s + t)
                    at = np_derived(seed, role, d0[keys[now]], d1[keys[now]]) % width
                    by = 1 + np_derived(seed, role + 1, d0[keys[now]], d1[keys[now]]) % (prime - 1)
                    rows[np.arange(len(now)), at] = (rows[np.arange(len(now)), at] + by) % prime
                rows[:, -1] = rhs[now]
                good = system.try_add(of[now], rows)
                used[now[good]] = j
                now = now[~good]
                if not len(now):
                    break
        failed = np.zeros(len(left), bool)
        failed[of[used < 0]] = True
        most = np.zeros(len(left), np.int64)
        np.maximum.at(most, of, used + 1)
        for i, (b, g) in enumerate(zip(left.tolist(), system.solutions())):
            solved[b], blocks[b] = g, max(1, most[i])
        firsts = np.cumsum([0, *(len(g) for g in solved)])
        row = {"g": np.concatenate(solved), "h": np.column_stack((firsts[:-1], q, p, blocks, seeds)).ravel()}
        off = np.zeros(len(left), bool)
        wrong = (np_evaluate(spec, row, d0[keys], d1[keys]) != value[keys]) & ~failed[of]
        wrong_before += int(wrong.sum())
        off[of[wrong]] = True
        done = ~(failed | off)
        tries[left[done]] = np.bincount(of, used + 1, len(left))[done].astype(np.int64)
        first_block += int((used == 0)[done[of]].sum())
        left = left[~done]
        if not len(left):
            break
    else:
        raise K.BuildError(f"shard {shard}: {spec.max_attempts} seeds were not enough for buckets {left[:5].tolist()}")
    return {"n_slots": len(row["g"]), "seed": 0, "attempts": attempts, "n_blocks": int(blocks.max()), "tries": int(tries.sum()), "first_block": first_block, "extra": wrong_before, "p": int(p.max()), "g": row["g"], "h": row["h"]}


def _xor(spec: Spec, shard: int, d0, d1, value) -> dict:
    """The buckets of a shard, each by itself; laid out as those of sparse filters."""
    local = bucket_of(spec, d0, d1) // spec.shards
    order = np.argsort(local, kind="stable")
    ends = np.searchsorted(local[order], np.arange(spec.buckets + 1))
    cells, directory, most, first = [], [], 1, 0
    for b in range(spec.buckets):
        keys = order[ends[b] : ends[b + 1]]
        g, seed, attempt = _xor_system(spec, shard, b, d0[keys], d1[keys], value[keys])
        cells.append(g)
        directory += [first, len(g), 0, 1, seed]
        first += len(g)
        most = max(most, attempt)
    return {"n_slots": first, "seed": 0, "attempts": most, "g": np.concatenate(cells), "h": directory}


def _xor_system(spec: Spec, shard: int, bucket: int, d0, d1, value) -> tuple[np.ndarray, int, int]:
    n = len(d0)
    slots = max(spec.s, math.ceil(n * (1 + spec.eps)))
    for attempt in range(1, spec.max_attempts + 1):
        seed = next_seed(spec.seed, shard, bucket, attempt)
        at = np.stack([np_derived(seed, CHOICE + t, d0, d1) % slots for t in range(spec.s)])
        rhs = value ^ K.masks(d0, d1, seed, spec.modulus)
        rows = K.XorRows(slots)
        for i in range(n):
            bits = 0
            for t in range(spec.s):
                bits ^= 1 << int(at[t, i])
            if not rows.try_add(bits, int(rhs[i])):
                break
        else:
            return rows.solution(), seed, attempt
    raise K.BuildError(f"shard {shard}: {spec.max_attempts} seeds were not enough for {n} keys in {slots} slots")


def _dict(spec: Spec, shard: int, d0, d1, value) -> dict:
    """Linear probing, laid out in one pass: keys by home slot, each at its home or after the key before."""
    n, slots = len(d0), max(1, math.ceil(len(d0) / spec.load))
    best = None
    for attempt in range(1, spec.tries + 1):
        seed = next_seed(spec.seed, shard, attempt)
        home = np_derived(seed, 1, d0, d1) % slots
        order = np.lexsort((d0, home))
        at = np.maximum.accumulate(home[order] - np.arange(n)) + np.arange(n)
        probe = int((at - home[order]).max(initial=0)) + 1
        if best is None or probe < best[0]:
            best = probe, seed, order, at
    probe, seed, order, at = best
    size = max(slots, int(at.max(initial=0)) + 1)
    keys, values = np.zeros(size, np.int64), np.full(size, -1, np.int64)
    keys[at], values[at] = d0[order], value[order]
    out = {"n_slots": slots, "seed": seed, "attempts": spec.tries, "extra": probe, "g": keys, "h": values}
    return out | ({"b": _membership(spec, shard, d0, d1, value)["b"]} if spec.kind == "dict_membership" else {})


def _membership(spec: Spec, shard: int, d0, d1, value) -> dict:
    words = membership_words(len(d0), spec)
    seed = next_seed(spec.seed, shard, 1)
    bits = np.zeros(words * 64, np.uint8)
    for at in membership_bits(d0, d1, next_seed(spec.seed, shard, 0), words * 64, spec.hashes):
        bits[at] = 1
    return {"n_slots": words * 64, "seed": seed, "attempts": 1, "g": None, "b": np.packbits(bits, bitorder="little").view("<i8")}


def membership_words(n: int, spec: Spec) -> int:
    return max(1, math.ceil(n * spec.bits_per_key / 64))


def membership_bits(d0, d1, seed: int, n_bits: int, hashes: int):
    first, step = np_derived(seed, 1, d0, d1) % n_bits, np_derived(seed, 2, d0, d1) % n_bits
    for j in range(hashes):
        yield (first + j * step) % n_bits


KERNELS: dict[str, Callable] = {"acyclic": _acyclic, "af_raw": _acyclic, "mutable": _acyclic, "matched": _matched, "peeled": _peeled, "sparse": _sparse, "xor": _xor, "dict": _dict, "membership": _membership, "dict_membership": _dict}


# --- builders ----------------------------------------------------------------------------------------------------------


def build_acyclic(df: DataFrame, key, value: str, *, k: int = 1, modulus: int | None = None, error: float = 2.0**-32, c: float = 2.5, endpoints: str = "distinct", family: str = "xx64", canonical: bool = False, shards: int | str = "auto", max_attempts: int = 64, seed: int = 42) -> Filter:
    """A key is an edge between two slots; the slots' residues and the key's mask add up to its value, and almost never to a value for other keys.

    ``canonical``: each tree has 0 at its least slot, whoever built it, and tree sizes are recorded.
    """
    check_c(c)
    if endpoints not in ("distinct", "independent") or family not in FAMILIES:
        raise ValueError(f"{endpoints}, {family}")
    n = df.count()
    return _build(df, key, value, Spec("acyclic", k=k, modulus=modulus_for(k, modulus, error), c=c, distinct=endpoints == "distinct", family=family, canonical=canonical, shards=shards_for(n, shards), max_attempts=max_attempts, seed=seed), n)


def build_peeled(df: DataFrame, key, value: str, *, k: int = 1, modulus: int | None = None, error: float = 2.0**-32, endpoints_per_key: int = 3, c: float = 1.25, shards: int | str = "auto", max_attempts: int = 128, seed: int = 42) -> Filter:
    """An acyclic filter with three slots for each key, in ranges of their own: peeling a random hypergraph needs about 1.23 slots a key, where a graph needs over 2.

    Later public knowledge answers the question of linear building below two slots a key that way.
    """
    if endpoints_per_key < 3 or c < 1.2:
        raise ValueError("three slots or more for each key, and 1.2 slots a key")
    n = df.count()
    return _build(df, key, value, Spec("peeled", k=k, modulus=modulus_for(k, modulus, min(error, 2.0**-2)), c=c, r=endpoints_per_key, shards=shards_for(n, shards), max_attempts=max_attempts, seed=seed), n)


def value_bits(df: DataFrame, value: str, least: int = 1) -> int:
    """Bits that hold every value of the set, ``least`` at least."""
    return max(least, int(df.agg(F.max(value)).first()[0] or 0).bit_length())


def plan_shards(df: DataFrame, key, approx: bool = False, per_shard: int = 1 << 16) -> int:
    """Shards for a set that isn't counted yet; ``approx`` estimates the distinct keys (for planning only: builds count exactly)."""
    names = key_columns(key)
    n = df.agg(F.approx_count_distinct(F.struct(*names))).first()[0] if approx else df.select(*names).distinct().count()
    return shards_for(n, "auto", per_shard)


def build_bitmap_map(df: DataFrame, key, value: str, *, k: int = 1, c: float = 2.5, seed: int = 42, shards: int | str = "auto") -> Filter:
    """The same without masks: exact on keys, some value for any other key."""
    check_c(c)
    check_k(k)
    n = df.count()
    return _build(df, key, value, Spec("af_raw", k=k, modulus=1 << k, c=c, shards=shards_for(n, shards), seed=seed), n)


def build_mutable(df: DataFrame, key, value: str, *, k: int = 1, modulus: int | None = None, error: float = 2.0**-32, c: float = 2.5, component_cap: int | str = "auto", shards: int | str = "auto", seed: int = 42) -> Filter:
    """An acyclic filter whose trees are all small, with each slot's tree kept, so that values can be changed."""
    check_c(c)
    n = df.count()
    parts = shards_for(n, shards)
    cap = component_bound(max(2, n // parts), c) if component_cap == "auto" else int(component_cap)
    return _build(df, key, value, Spec("mutable", k=k, modulus=modulus_for(k, modulus, error), c=c, shards=parts, component_cap=cap, canonical=True, seed=seed, max_attempts=256), n)


def build_matched(df: DataFrame, key, value: str, *, k: int = 1, error: float = 2.0**-32, r: int = 2, slots_factor: float = 2.5, matching: str = "sorted", seed: int = 42, shards: int | str = "auto") -> Filter:
    """The measured competitor, reconstructed from its outline: one table tells which of r slots is a key's own, a second holds the value there.

    matching: ``sorted`` finds it in rounds over all keys left, in n log n time as the outline says; ``peel`` is this engine's own linear way.
    """
    if matching not in ("sorted", "peel"):
        raise ValueError(matching)
    if r < 2:
        raise ValueError("with one position for each key, two keys collide almost surely")
    check_k(k)
    n = df.count()
    return _build(df, key, value, Spec("matched", k=k, c=slots_factor, r=r, matching=matching, q_bits=math.ceil(math.log2(r / error)), shards=shards_for(n, shards), seed=seed), n)


def _check_sparse(k: int, eps: float, s: int, p_bits: int, allow_s1: bool) -> None:
    check_k(k)
    if p_bits <= k:
        raise ValueError("p_bits must be above k")
    if p_bits > 61:
        raise ValueError("residues have 61 bits at most")
    if s < 1 or s == 1 and not allow_s1:
        raise ValueError("s = 1 needs very many blocks; allow_s1 makes it possible")
    if eps <= 0:
        raise ValueError("eps must be above 0")


def build_sparse_linear(df: DataFrame, key, value: str, *, k: int, eps: float = 0.1, s: int = 3, p_bits: int = 31, seed: int = 42, max_blocks: int = 64, field: str = "primitive", allow_s1: bool = False, limit: int = 4096) -> Filter:
    """Each key a row with s coefficients over a prime field; the table solves all rows. One task; refused above ``limit`` keys."""
    _check_sparse(k, eps, s, p_bits, allow_s1)
    n = df.count()
    if n > limit:
        raise ValueError(f"{n} keys in one system; build_bucketed_sparse splits them")
    return _build(df, key, value, Spec("sparse", k=k, eps=eps, s=s, p_bits=p_bits, shards=1, seed=seed, max_blocks=max_blocks, field=field), n)


def choose_bucket_seed(df: DataFrame, key, buckets: int, delta: float = 4.5, seed: int = 42, candidates: int = 4, rounds: int = 16) -> tuple[int, int, int]:
    """(seed, its largest bucket, seeds tried): the first under which no bucket has (1 + delta) times the mean. One job tries several seeds."""
    kinds = check_key_types(df, key)
    d0, d1 = digests(key, kinds)
    n = df.count()
    limit = (1 + delta) * n / buckets
    bucket_tail(max(1, n), buckets, delta)
    for start in range(0, candidates * rounds, candidates):
        seeds = [next_seed(seed, 77, start + i) for i in range(candidates)]
        rows = df.select(d0.alias("d0"), d1.alias("d1")).select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), shard_of(buckets, s).alias("bucket")) for i, s in enumerate(seeds)])).alias("x"))
        worst = {r["i"]: r["n"] for r in rows.groupBy("x.i", "x.bucket").count().groupBy("i").agg(F.max("count").alias("n")).collect()}
        for i, s in enumerate(seeds):
            if worst.get(i, 0) < limit or n == 0:
                return s, worst.get(i, 0), start + i + 1
    raise K.BuildError("no bucket hash was even enough")


def bucket_count(n: int, bucket_c: float = 2.0) -> int:
    return max(1, round(n / (bucket_c * math.log(max(n, 3)))))


def build_bucketed_sparse(df: DataFrame, key, value: str, *, k: int, eps: float = 0.1, s: int = 3, p_bits: int = 31, bucket_c: float = 2.0, delta: float = 4.5, seed: int = 42, max_blocks: int = 64, field: str = "primitive") -> Filter:
    """A sparse-linear filter for each of n/(c log n) buckets, many of them in a shard: building becomes almost linear, memory stays near n."""
    _check_sparse(k, eps, s, p_bits, False)
    if bucket_c <= 1:
        raise ValueError("bucket_c must be above 1")
    n = df.count()
    shards = shards_for(n, "auto")
    per_shard = -(-bucket_count(n, bucket_c) // shards)
    chosen, _, _ = choose_bucket_seed(df, key, shards * per_shard, delta, seed)
    return _build(df, key, value, Spec("sparse", k=k, eps=eps, s=s, p_bits=p_bits, shards=shards, buckets=per_shard, seed=chosen, max_blocks=max_blocks, field=field), n)


def bucketed(builder: Callable, df: DataFrame, key, value: str, *, bucket_c: float = 2.0, **options) -> Filter:
    """Any builder over n/(c log n) buckets: each is built by itself, and a lookup evaluates one more hash."""
    if builder is build_sparse_linear:
        return build_bucketed_sparse(df, key, value, bucket_c=bucket_c, **options)
    if builder is build_xor_sparse:
        return builder(df, key, value, per_bucket=max(1, round(bucket_c * math.log(max(df.count(), 3)))), **options)
    return builder(df, key, value, shards=bucket_count(df.count(), bucket_c), **options)


def build_xor_sparse(df: DataFrame, key, value: str, *, k: int, error: float = 2.0**-20, eps: float = 0.25, s: int = 3, seed: int = 42, per_bucket: int = 256) -> Filter:
    """s positions over GF(2), combined by exclusive or: the later, simpler relative."""
    n = df.count()
    shards = shards_for(n, "auto")
    buckets = -(-shards_for(n, "auto", per_bucket) // shards)
    return _build(df, key, value, Spec("xor", k=k, modulus=modulus_for(k, None, error), eps=eps, s=s, shards=shards, buckets=buckets, seed=seed, max_attempts=512), n)


def build_hash_dict(df: DataFrame, key, value: str, *, k: int = 60, load: float = 0.5, seed: int = 42, shards: int | str = "auto") -> Filter:
    """Open addressing with linear probing over 64-bit digests."""
    n = df.count()
    return _build(df, key, value, Spec("dict", k=k, load=load, shards=shards_for(n, shards), seed=seed), n)


def build_low_collision_dict(df: DataFrame, key, value: str, *, k: int = 60, load: float = 0.5, tries: int = 8, seed: int = 42, shards: int | str = "auto") -> Filter:
    """The same with the best of several hashes: the one with the shortest longest probe."""
    n = df.count()
    return _build(df, key, value, Spec("dict", k=k, load=load, tries=tries, shards=shards_for(n, shards), seed=seed), n)


def _bits(error: float) -> dict:
    hashes = max(1, math.ceil(math.log2(1 / error)))
    return {"hashes": hashes, "bits_per_key": hashes / math.log(2)}


def build_membership(df: DataFrame, key, *, error: float = 2.0**-8, seed: int = 42, shards: int | str = "auto") -> Filter:
    """A bit array: no false negatives, the given share of false positives."""
    n = df.count()
    return _build(df.dropDuplicates(key_columns(key)), key, None, Spec("membership", k=1, shards=shards_for(n, shards), seed=seed, **_bits(error)), n)


def build_dict_with_membership(df: DataFrame, key, value: str, *, k: int = 60, error: float = 2.0**-8, load: float = 0.5, seed: int = 42, shards: int | str = "auto") -> Filter:
    """A dictionary asked only for keys that a bit array lets through."""
    n = df.count()
    return _build(df, key, value, Spec("dict_membership", k=k, load=load, shards=shards_for(n, shards), seed=seed, **_bits(error)), n)


def expected_attempts(spec: Spec) -> float:
    """Draws of the graph that a shard should need."""
    return 1 / acyclic_probability(spec.c, spec.distinct)
