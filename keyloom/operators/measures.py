"""Cost and accuracy measures of filters. Builds record theirs in ``tables``; these functions aggregate them."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.functions.hashing import CHOICE, check_key_types, digests, key_columns, np_derived, shard_of
from keyloom.functions.packing import width_of
from keyloom.operators import kernels as K
from keyloom.operators.lookup import Filter, lookup, np_evaluate
from keyloom.plans.params import Spec, acyclic_probability, bucket_tail


def slot_bits(spec: Spec) -> int:
    """Bits of one slot, all tables together; for sparse filters the width of the largest prime."""
    if spec.kind in ("acyclic", "mutable", "af_raw", "xor", "peeled"):
        return width_of(spec.modulus)
    if spec.kind == "matched":
        return spec.q_bits + spec.k
    if spec.kind == "sparse":
        return spec.p_bits
    if spec.kind in ("dict", "dict_membership"):
        return 64 + spec.k
    return 1


def size_bits(filter: Filter) -> dict[str, float]:
    """Bits of the table at exact width, of the sides (seeds, primes, directory), of what only updates need, and of all that a lookup needs for each key."""
    row = filter.tables.agg(F.sum("n_slots").alias("slots"), F.count("*").alias("shards"), F.sum(F.coalesce(F.size("b"), F.lit(0))).alias("words")).first()
    spec = filter.spec
    slots, shards = row["slots"] or 0, row["shards"] * max(1, spec.buckets)
    table = slots * slot_bits(spec) + (64 * max(0, row["words"] or 0) if spec.kind == "dict_membership" else 0)
    side = shards * (64 + 32 + (spec.p_bits if spec.kind == "sparse" else 0))
    graph = filter.n * 2 * max(1, math.ceil(math.log2(max(2, slots)))) if spec.kind == "mutable" else 0
    return {"table": table, "side": side, "update": graph, "per_key": (table + side) / max(1, filter.n)}


def predicted_bits(spec: Spec, n: int) -> float:
    """The space that formulas give."""
    if spec.kind in ("acyclic", "mutable", "af_raw", "peeled"):
        return math.ceil(spec.c * n) * width_of(spec.modulus)
    if spec.kind == "matched":
        return spec.c * n * (spec.q_bits + spec.k)
    if spec.kind == "sparse":
        return n * (1 + spec.eps) * spec.p_bits + (spec.shards * max(1, spec.buckets) * spec.p_bits if spec.shards * max(1, spec.buckets) > 1 else 0)
    if spec.kind == "xor":
        return math.ceil(n * (1 + spec.eps)) * width_of(spec.modulus)
    if spec.kind == "membership":
        return n * spec.bits_per_key
    return n / spec.load * (64 + spec.k) + (n * spec.bits_per_key if spec.kind == "dict_membership" else 0)


def lookup_cost(spec: Spec) -> dict[str, int]:
    """Hash evaluations and table reads of one lookup (of one tried block for sparse filters); one more hash if the set is sharded."""
    hashes, reads = {"acyclic": (3, 2), "mutable": (3, 2), "af_raw": (2, 2), "matched": (spec.r + 1, spec.r + 1), "peeled": (spec.r + 1, spec.r), "sparse": (1 + 2 * spec.s, spec.s), "xor": (spec.s + 1, spec.s), "dict": (1, 1), "membership": (spec.hashes, spec.hashes), "dict_membership": (spec.hashes + 1, spec.hashes + 1)}[spec.kind]
    return {"hashes": hashes + (spec.shards > 1 or spec.buckets > 0), "reads": reads}


def counted_cost(df: DataFrame, filter: Filter, key) -> dict[str, float]:
    """Hash evaluations and table reads that looking these keys up takes, counted while the kernels' lookup runs over them: (keys, hashes, reads)."""
    if filter.spec.kind in ("membership", "dict_membership"):
        raise ValueError("only filters that look up one table are counted")
    spec, names = filter.spec, [f.name for f in filter.tables.schema]
    d0, d1 = digests(key, filter.key_types, spec.family)
    keys = df.select(d0.alias("d0"), d1.alias("d1")).select(shard_of(spec.shards, spec.seed, spec.family).alias("shard"), "d0", "d1")

    def run(asked: pa.Table, rows: pa.Table) -> pa.Table:
        tally: dict[str, int] = {"hashes": 0, "reads": 0}
        if asked.num_rows and rows.num_rows:
            row = {n: rows.column(n)[0].as_py() for n in names}
            np_evaluate(spec, row, asked.column("d0").to_numpy(), asked.column("d1").to_numpy(), tally)
        return pa.table({"n": [asked.num_rows], "hashes": [tally["hashes"]], "reads": [tally["reads"]]})

    counted = keys.groupBy("shard").cogroup(filter.tables.groupBy("shard")).applyInArrow(run, "n long, hashes long, reads long")
    row = counted.agg(F.sum("n").alias("keys"), F.sum("hashes").alias("hashes"), F.sum("reads").alias("reads")).first()
    return {k: float(v or 0) for k, v in row.asDict().items()}


def member_mismatches(df: DataFrame, filter: Filter, key, value: str) -> int:
    """Keys of the set that a lookup doesn't give their value: 0 for every filter."""
    return lookup(df, filter, key, "_v").where(~F.col("_v").eqNullSafe(F.col(value).cast("long"))).count()


def false_value_rate(filter: Filter, absent: DataFrame, key) -> dict[str, float]:
    """The share of absent keys that get a value, the bound for it, and how many standard deviations it is off."""
    row = lookup(absent, filter, key, "_v").agg(F.count("*").alias("n"), F.count("_v").alias("hits")).first()
    n, hits, bound = row["n"], row["hits"], min(1.0, filter.spec.error)
    sigma = math.sqrt(max(bound * (1 - bound) / max(1, n), 1e-300))
    return {"n": n, "hits": hits, "rate": hits / max(1, n), "bound": bound, "sigmas": (hits / max(1, n) - bound) / sigma}


def build_stats(filter: Filter) -> dict[str, float]:
    """Seconds in kernels, draws, tree sizes, blocks and tries, from the shards' rows."""
    row = filter.tables.agg(F.sum("seconds").alias("kernel_seconds"), F.avg("attempts").alias("mean_attempts"), F.max("attempts").alias("max_attempts"), F.max("max_component").alias("max_component"), F.sum("extra").alias("extra"), F.max("n_blocks").alias("max_blocks"), (F.sum("tries") / F.sum("n_keys")).alias("mean_tries"), (F.sum("first_block") / F.sum("n_keys")).alias("at_first_block"), F.sum("n_keys").alias("n"), F.max("n_keys").alias("max_shard")).first()
    return {k: float(v) if v is not None else 0.0 for k, v in row.asDict().items()}


def measure_build(builder: Callable[[int], Filter], trials: int = 45, warm_up: int = 1) -> dict[str, float]:
    """Mean wall and kernel seconds, and draws, over builds with seeds 1 to ``trials``, each a job of its own."""
    wall, kernel, draws = [], [], []
    for seed in range(1 - warm_up, trials + 1):
        start = time.perf_counter()
        stats = build_stats(builder(seed))
        if seed > 0:
            wall.append(time.perf_counter() - start)
            kernel.append(stats["kernel_seconds"])
            draws.append(stats["mean_attempts"])
    return {"trials": trials, "wall_seconds": float(np.mean(wall)), "kernel_seconds": float(np.mean(kernel)), "draws": float(np.mean(draws))}


def measure_kernels(df: DataFrame, key, value: str, spec: Spec, trials: int = 45) -> dict[str, float]:
    """Mean kernel seconds (all shards together) and draws over the seeds 1 to ``trials``: keys are dealt to shards once, and each shard's task builds it under every seed."""
    from keyloom.operators.build import _digested, build_table

    kinds = check_key_types(df, key)

    def run(table: pa.Table) -> pa.Table:
        shard = table.column("shard")[0].as_py()
        build_table(replace(spec, seed=0), table)  # the first build of a process pays for its imports
        rows = [build_table(replace(spec, seed=s), table) for s in range(1, trials + 1)]
        cells = {c: [r.column(c)[0].as_py() for r in rows] for c in ("seconds", "attempts", "n_slots")}
        return pa.table({"shard": pa.array([shard] * trials, pa.int32()), "trial": pa.array(range(1, trials + 1), pa.int32()), **{k: pa.array(v) for k, v in cells.items()}}).cast(pa.schema([("shard", pa.int32()), ("trial", pa.int32()), ("seconds", pa.float64()), ("attempts", pa.int64()), ("n_slots", pa.int64())]))

    made = _digested(df, key, value, kinds, spec).groupBy("shard").applyInArrow(run, "shard int, trial int, seconds double, attempts long, n_slots long")
    each = made.groupBy("trial").agg(F.sum("seconds").alias("seconds"), F.avg("attempts").alias("draws"), F.sum("n_slots").alias("slots"))
    row = each.agg(F.count("*").alias("trials"), F.avg("seconds").alias("kernel_seconds"), F.stddev_samp("seconds").alias("kernel_seconds_sd"), F.avg("draws").alias("draws"), F.max("slots").alias("slots")).first()
    return {k: float(v or 0.0) for k, v in row.asDict().items()}


def speedup(slow: dict[str, float], fast: dict[str, float], what: str = "kernel_seconds") -> float:
    return slow[what] / fast[what]


def measure_lookup(df: DataFrame, filter: Filter, key) -> dict[str, float]:
    """Rows a second of a lookup whose result is only counted."""
    start = time.perf_counter()
    row = lookup(df, filter, key, "_v").agg(F.count("*").alias("n"), F.count("_v").alias("hits")).first()
    seconds = time.perf_counter() - start
    return {"rows": row["n"], "hits": row["hits"], "seconds": seconds, "rows_per_second": row["n"] / seconds}


def acyclic_rate(n: int, c: float, trials: int, distinct: bool = True, seed: int = 1) -> dict[str, float]:
    """The share of random graphs without a cycle, and what the formula gives; the largest trees of those; vertices on trees."""
    keys = np.arange(n, dtype=np.int64)
    slots, good, largest, touched = math.ceil(c * n), 0, [], []
    for t in range(trials):
        u, v = K.endpoints(keys, keys, seed * 1_000_003 + t, slots, distinct)
        if (peeled := K.is_forest(u, v, slots)) is not None:
            good += 1
            forest = K.solve_forest(peeled, u, v, np.zeros(n, np.int64), slots, 2)
            largest.append(int(forest.sizes.max()))
            touched.append(len(np.unique(np.concatenate((u, v)))))
    return {"rate": good / trials, "formula": acyclic_probability(c, distinct), "max_component": float(np.max(largest, initial=0)), "mean_max_component": float(np.mean(largest)) if largest else 0.0, "tree_vertices": float(np.mean(touched)) if touched else 0.0}


def _dealt(df: DataFrame, key, per_task: int) -> tuple[DataFrame, int]:
    """(part, d0, d1): the digests of all keys that aren't NULL, dealt to tasks of about ``per_task``; how many tasks."""
    d0, d1 = digests(key, check_key_types(df, key))
    keys = df.dropna(subset=key_columns(key)).select(d0.alias("d0"), d1.alias("d1"))
    parts = max(1, round(keys.count() / per_task))
    return keys.select(F.pmod("d0", F.lit(parts)).alias("part"), "d0", "d1"), parts


def _draws(table: pa.Table, each: int, least: int):
    """(d0, d1, seed) of sets of ``each`` rows, ``least`` sets or more, until every key is in one. A key that is taken again has another seed."""
    d0, d1 = (table.column(c).to_numpy() for c in ("d0", "d1"))
    order = np.lexsort((d1, d0))
    d0, d1 = d0[order], d1[order]
    for nth in range(max(least, -(-len(d0) // each))):
        at = np.arange(nth * each, (nth + 1) * each)
        yield d0[at % len(d0)], d1[at % len(d0)], 1 + at // len(d0)


def acyclic_rates(df: DataFrame, key, n: int, cs: tuple[float, ...], trials: int) -> dict[tuple[float, bool], dict[str, float]]:
    """What ``acyclic_rate`` tells, for each c and both ways to draw endpoints, of graphs whose edges are the keys of a table."""
    dealt, parts = _dealt(df, key, 10 * n)

    def run(table: pa.Table) -> pa.Table:
        rows = {(c, distinct): [0, 0, 0, 0, 0] for c in cs for distinct in (True, False)}
        for d0, d1, seed in _draws(table, n, -(-trials // parts)):
            for (c, distinct), row in rows.items():
                slots = math.ceil(c * n)
                u, v = K.endpoints(d0, d1, seed, slots, distinct)
                row[0] += 1
                if (peeled := K.is_forest(u, v, slots)) is not None:
                    largest = int(K.solve_forest(peeled, u, v, np.zeros(n, np.int64), slots, 2).sizes.max())
                    row[1:] = row[1] + 1, max(row[2], largest), row[3] + largest, row[4] + int((np.bincount(u, minlength=slots) + np.bincount(v, minlength=slots) > 0).sum())
        return pa.Table.from_pylist([dict(zip(("c", "distinct", "graphs", "good", "most", "largest", "touched"), (*k, *row))) for k, row in rows.items()])

    made = dealt.groupBy("part").applyInArrow(run, "c double, distinct boolean, graphs long, good long, most long, largest long, touched long")
    sums = made.groupBy("c", "distinct").agg(F.max("most").alias("most"), *(F.sum(x).alias(x) for x in ("graphs", "good", "largest", "touched"))).orderBy("c", F.desc("distinct")).collect()  # a row for each c and way
    return {(r["c"], r["distinct"]): {"rate": r["good"] / r["graphs"], "formula": acyclic_probability(r["c"], r["distinct"]), "max_component": float(r["most"]), "mean_max_component": r["largest"] / max(1, r["good"]), "tree_vertices": r["touched"] / max(1, r["good"])} for r in sums}


def bucket_load(df: DataFrame, key, buckets: int, seed: int = 42, delta: float = 4.5) -> dict[str, float]:
    """The largest and mean bucket, the share of buckets above (1 + delta) times the mean, and the bound on that chance."""
    kinds = check_key_types(df, key)
    d0, d1 = digests(key, kinds)
    counts = df.select(d0.alias("d0"), d1.alias("d1")).groupBy(shard_of(buckets, seed).alias("bucket")).count()
    row = counts.agg(F.sum("count").alias("n"), F.max("count").alias("most")).first()
    n, most = row["n"] or 0, row["most"] or 0
    above = counts.where(F.col("count") > (1 + delta) * n / buckets).count()
    return {"n": n, "max": most, "mean": n / buckets, "above": above / buckets, "bound": bucket_tail(max(1, n), buckets, delta)}


def full_rank_rate(r: int, q: int, s: int, p: int, trials: int, seed: int = 1) -> float:
    """The share of random matrices, with s entries other than 0 in each of r rows of q, that have full rank."""
    g, good = np.random.default_rng(seed), 0
    for _ in range(trials):
        rows = K.Echelon(q, p)
        ok = True
        for _ in range(r):
            row = np.zeros(q + 1, np.int64)
            row[g.choice(q, s, replace=False)] = g.integers(1, p, s)
            ok = ok and rows.try_add(row)
        good += ok
    return good / trials


def sparse_rows(d0: np.ndarray, d1: np.ndarray, seed: np.ndarray, q: int, s: int, p: int) -> np.ndarray:
    """A row for each key: s different places of q with residues other than 0, and a last column of zeros."""
    rows, taken = np.zeros((len(d0), q + 1), np.int64), np.zeros((len(d0), 0), np.int64)
    for t in range(s):
        at = np_derived(seed, CHOICE + 2 * t, d0, d1) % (q - t)
        for i in range(t):  # places taken already, from the least on, are stepped over
            at = at + (at >= taken[:, i])
        rows[np.arange(len(d0)), at] = 1 + np_derived(seed, CHOICE + 2 * t + 1, d0, d1) % (p - 1)
        taken = np.sort(np.column_stack((taken, at)), axis=1)
    return rows


def full_rank_rates(df: DataFrame, key, shapes: list[tuple[int, int, int, int]], trials: int) -> dict[tuple[int, int, int, int], float]:
    """For each shape (q, r, s, p) the share of matrices of full rank whose rows are drawn from the keys of a table; ``trials`` matrices or more, until every key is in one."""
    dealt, parts = _dealt(df, key, 2_000)

    def run(table: pa.Table) -> pa.Table:
        rows = []
        for q, r, s, p in shapes:
            made = [sparse_rows(*keys, q, s, p) for keys in _draws(table, r, -(-trials // parts))]
            systems = K.Echelons(np.full(len(made), q), np.full(len(made), p), r)
            good = np.arange(len(made))
            for i in range(r):
                good = good[systems.try_add(good, np.stack([made[m][i] for m in good]))] if len(good) else good
            rows.append({"q": q, "r": r, "s": s, "p": p, "made": len(made), "good": len(good)})
        return pa.Table.from_pylist(rows)

    made = dealt.groupBy("part").applyInArrow(run, "q long, r long, s long, p long, made long, good long")
    sums = made.groupBy("q", "r", "s", "p").agg(F.sum("made").alias("made"), F.sum("good").alias("good")).orderBy("q", "r", "s").collect()  # a row for each shape
    return {(x["q"], x["r"], x["s"], x["p"]): x["good"] / x["made"] for x in sums}


def pre_repair_errors(filter: Filter) -> int:
    """Members that an earlier block answered wrongly, in systems that were rebuilt for that; all builds count."""
    return filter.tables.agg(F.sum("extra")).first()[0] or 0 if filter.spec.kind == "sparse" else 0


def sparse_member_error_bound(spec: Spec, tries: int, n: int, p: int) -> float:
    """The expected members that an earlier block answers for: one chance of 2^k / p for each block tried before a member's own."""
    return (tries - n) * 2.0**spec.k / p


def space_table(k: int, errors: list[float], eps: float = 0.1, c: float = 2.5, r: int = 2, load: float = 0.5) -> list[tuple[str, float, float]]:
    """(method, error, bits for each key) by the formulas."""
    rows = []
    for e in errors:
        bits = -math.log2(e)
        rows += [
            ("acyclic", e, c * (k + math.ceil(bits))),
            ("matched", e, c * (math.ceil(math.log2(r / e)) + k)),
            ("sparse", e, (1 + eps) * (k + 1 + math.ceil(bits))),
            ("membership", e, math.ceil(bits) / math.log(2)),
            ("dict_membership", e, math.ceil(bits) / math.log(2) + (64 + k) / load),
        ]
    return rows


def fit_slope(df: DataFrame, n: str, seconds: str, by: str) -> DataFrame:
    """(method, slope): the power of n by which seconds grow."""
    return df.groupBy(by).agg(F.regr_slope(F.log(seconds), F.log(n)).alias("slope"))


def report(df: DataFrame, how: str = "cube", keys: tuple[str, str] = ("method", "n"), value: str = "measured") -> DataFrame:
    """Means of a measure by the given keys: cube, rollup, or pivot over the second key."""
    if how == "pivot":
        return df.groupBy(keys[0]).pivot(keys[1]).agg(F.avg(value))
    return getattr(df, how)(*keys).agg(F.avg(value).alias(value), F.count("*").alias("rows"))
