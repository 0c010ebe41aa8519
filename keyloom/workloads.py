"""The experiment workloads on the given tables: pair fixtures, and measurements as rows (method, n, parameter, measure, measured)."""

from __future__ import annotations

import time
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyloom.functions import algebra
from keyloom.functions.numtheory import choose_primes
from keyloom.operators import build, measures
from keyloom.operators.lookup import Filter
from keyloom.operators.mutable import edges, update_matched, update_values
from keyloom.operators.relational import dictionary, indegree
from keyloom.plans.scratch import written
from keyloom.sources.tables import links, raw_links, table

MEASURED = "method string, n long, parameter string, measure string, measured double"
#: Bits of a sparse filter's prime beyond those of the value and the error.
SPARE_BITS = 8
LINE_KEYS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


# --- pair fixtures: (key..., value) ------------------------------------------------------------------------------------


def indeg_url(spark: SparkSession, d: str) -> DataFrame:
    return indegree(links(table(spark, d, "pages")), "target")


def indeg_path(spark: SparkSession, d: str) -> DataFrame:
    return indegree(raw_links(table(spark, d, "pages")), "path")


def _counts(name: str, key: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: indegree(table(spark, d, name).select(key), key)


indeg_order, indeg_part, indeg_supplier = (_counts("lineitem", k) for k in LINE_KEYS[:3])
indeg_customer, indeg_user = _counts("orders", "o_custkey"), _counts("events", "user_id")


def line_qty(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").groupBy(*LINE_KEYS).agg(F.max("l_quantity").cast("long").alias("value"))


def nation_region(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "nation").select("n_nationkey", F.col("n_regionkey").cast("long").alias("value"))


def label(column: str) -> Callable[[SparkSession, str], DataFrame]:
    value = "2 * max(quality) + max(toxic)" if column == "pair" else f"max({column})"
    return lambda spark, d: table(spark, d, "labels").groupBy("doc_id").agg(F.expr(value).cast("long").alias("value"))


def coded(name: str, keys: list[str], column: str) -> Callable[[SparkSession, str], tuple[DataFrame, DataFrame]]:
    """(pairs, codes): the column by its place among the sorted values."""

    def make(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
        rows = table(spark, d, name).groupBy(*keys).agg(F.min(column).alias(column))
        codes = dictionary(rows, column)
        return rows.join(codes, column).select(*keys, F.col("code").alias("value")), codes

    return make


def changes(pairs: DataFrame, key: str, every: int) -> DataFrame:
    """A new value for every so-many-th key."""
    return pairs.where(F.col(key) % every == 0).select(key, (F.col("value") % 17 + 1).alias("value"))


# --- measurements ------------------------------------------------------------------------------------------------------


def _rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(m, int(n), str(p), what, float(x)) for m, n, p, what, x in rows], MEASURED)


def creation(spark: SparkSession, d: str, trials: int = 45, c: float = 2.5, error: float = 2.0**-32, names: tuple[str, ...] = ("indeg_url", "indeg_part", "indeg_order", "line_qty")) -> DataFrame:
    """Creation seconds, draws, speed-up and bits of the acyclic filter and its competitor, over key sets of growing size (the in-degrees of URLs first) and seeds 1 to ``trials``.

    Seconds are those of all shards' kernels, under every seed; a build as a whole is timed once.
    """
    rows = []
    for name in names:
        pairs, _ = written(globals()[name](spark, d), name)
        key = LINE_KEYS if name == "line_qty" else [c for c in pairs.columns if c != "value"]
        n, k = pairs.count(), build.value_bits(pairs, "value", 6)
        make = {
            "acyclic": lambda: build.build_acyclic(pairs, key, "value", k=k, error=error, c=c),
            "acyclic_independent": lambda: build.build_acyclic(pairs, key, "value", k=k, error=error, c=c, endpoints="independent"),
            "matched": lambda: build.build_matched(pairs, key, "value", k=k, error=error, slots_factor=c),
            "matched_peel": lambda: build.build_matched(pairs, key, "value", k=k, error=error, slots_factor=c, matching="peel"),
        }
        found = {}
        for m, f in make.items():
            start = time.perf_counter()
            made = f()
            wall = time.perf_counter() - start
            found[m] = measures.measure_kernels(pairs, key, "value", made.spec, trials)
            size = measures.size_bits(made)["per_key"]
            rows += [(m, n, name, what, x) for what, x in found[m].items()]
            rows += [(m, n, name, "wall_seconds_once", wall), (m, n, name, "bits_per_key", size), (m, n, name, "gb_at_1.1e9_keys", size * 1.1e9 / 8e9)]
        for other in ("matched", "matched_peel"):
            rows.append(("acyclic", n, name, f"speedup_over_{other}", measures.speedup(found[other], found["acyclic"])))
    return _rows(spark, rows)


def c_sweep(spark: SparkSession, d: str, n: int = 5_000, trials: int = 100) -> DataFrame:
    """Acyclicity, draws and tree sizes over c, for both ways to draw endpoints: graphs of n order keys each, ``trials`` or more, until every key is in one."""
    rows = []
    found = measures.acyclic_rates(table(spark, d, "orders").select("o_orderkey"), "o_orderkey", n, (2.05, 2.09, 2.25, 2.5, 3.0, 4.0), trials)
    for (c, distinct), stats in found.items():
        rows += [("distinct" if distinct else "independent", n, c, what, x) for what, x in stats.items()]
    return _rows(spark, rows)


def error_rates(spark: SparkSession, d: str, absent_keys: int = 100_000) -> DataFrame:
    """False values on absent keys against the bounds, for every filter: natural absents (orders without lines, documents without labels) and shifted keys, errors from 2^-2 to 2^-8.

    A sparse filter's error follows from its prime and the blocks that it has; its prime has SPARE_BITS more than one block needs,
    as in a smaller field too many members are answered by earlier blocks, and small buckets find no prime.
    """
    orders, _ = written(indeg_order(spark, d), "pairs")
    labels, _ = written(label("toxic")(spark, d), "labels")
    sets = {
        "orders": (orders, "l_orderkey", 5, table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey")).join(orders, "l_orderkey", "left_anti")),
        "labels": (labels, "doc_id", 1, table(spark, d, "documents").select("doc_id").join(labels, "doc_id", "left_anti")),
    }
    rows = []
    for name, (pairs, key, k, natural) in sets.items():
        shifted = spark.range(absent_keys).select((F.col("id") + 10**9).alias(key))
        some, _ = written(pairs.orderBy(key).limit(400), "some")
        for bits in (2, 4, 6, 8):
            error = 2.0**-bits
            made = {
                "acyclic": build.build_acyclic(pairs, key, "value", k=k, error=error),
                "matched": build.build_matched(pairs, key, "value", k=k, error=error),
                "peeled": build.build_peeled(pairs, key, "value", k=k, error=error),
                "xor": build.build_xor_sparse(pairs, key, "value", k=k, error=error),
                "membership": build.build_membership(pairs, key, error=error),
                "bslf": build.build_bucketed_sparse(pairs, key, "value", k=k, p_bits=k + bits + SPARE_BITS),
                "sparse": build.build_sparse_linear(some, key, "value", k=k, p_bits=k + bits + SPARE_BITS),
            }
            for m, f in made.items():
                away = natural if m != "sparse" else natural.unionByName(pairs.select(key).join(some, key, "left_anti"))
                for where, keys in (("shifted", shifted), ("natural", away)):
                    found = measures.false_value_rate(f, keys, key)
                    if f.spec.kind == "sparse":  # every block may answer: the bound grows with the blocks that there are
                        bound = min(1.0, f.blocks() * 2.0**k / 2.0 ** (f.spec.p_bits - 1))
                        found |= {"bound": bound, "sigmas": min(0.0, found["rate"] - bound)}
                    rows += [(m, f.n, f"{name} 2^-{bits} {where}", what, x) for what, x in found.items()]
    return _rows(spark, rows)


def update_costs(spark: SparkSession, d: str) -> DataFrame:
    """Slots written, rows written again and seconds for each changed key: both ways of the mutable filter, and the competitor."""
    pairs, _ = written(indeg_order(spark, d), "pairs")
    f = build.build_mutable(pairs, "l_orderkey", "value", k=5, shards=16)
    graph, _ = written(edges(f, pairs, "l_orderkey", "value"), "graph")
    other = build.build_matched(pairs, "l_orderkey", "value", k=5, shards=16)
    rows = []
    for every in (100, 10):
        new, _ = written(changes(pairs, "l_orderkey", every), "changes")
        n = new.count()
        for mode in ("recompute", "shift"):
            start = time.perf_counter()
            _, _, deltas = update_values(f, graph, new, "l_orderkey", mode=mode)
            seconds = time.perf_counter() - start
            rows += [(f"mutable_{mode}", f.n, f"1/{every}", "slots_per_key", deltas.count() / max(1, n)), (f"mutable_{mode}", f.n, f"1/{every}", "seconds_per_key", seconds / max(1, n))]
        start = time.perf_counter()
        cells = update_matched(other, new, "l_orderkey")[1]
        seconds = time.perf_counter() - start
        rows += [("matched", f.n, f"1/{every}", "slots_per_key", cells.count() / max(1, n)), ("matched", f.n, f"1/{every}", "seconds_per_key", seconds / max(1, n))]
    one = pairs.orderBy("l_orderkey").limit(1).select("l_orderkey", (F.col("value") % 17 + 1).alias("value"))
    start = time.perf_counter()
    _, _, deltas = update_values(f, graph, one, "l_orderkey")
    touched = deltas.select("shard").distinct()
    again = graph.join(touched, "shard", "left_semi").count()
    rows += [("mutable_recompute", f.n, "one key", "seconds", time.perf_counter() - start), ("mutable_recompute", f.n, "one key", "slots", deltas.count()), ("mutable_recompute", f.n, "one key", "edges_written_again", again)]
    rows.append(("mutable", f.n, "", "max_component", measures.build_stats(f)["max_component"]))
    return _rows(spark, rows)


def sparse_sweep(spark: SparkSession, d: str, sizes: tuple[int, ...] = (50, 100, 200, 400), eps: tuple[float, ...] = (0.05, 0.1, 0.2, 0.5)) -> DataFrame:
    """Seconds, tries and blocks of the sparse-linear filter over n part keys (all, if there are fewer), eps and s; s = 1 is the ablation."""
    pairs, _ = written(indeg_part(spark, d), "pairs")
    total = pairs.count()
    rows = []
    for n in sorted({min(n, total) for n in sizes}):
        some = pairs.orderBy("l_partkey").limit(n)
        for e in eps:
            for s in (1, 2, 3, 4):
                f = build.build_sparse_linear(some, "l_partkey", "value", k=7, eps=e, s=s, allow_s1=True, max_blocks=2_000 if s == 1 else 64)
                stats = measures.build_stats(f)
                rows += [(f"s={s}", n, e, what, stats[what]) for what in ("kernel_seconds", "mean_tries", "max_blocks", "at_first_block", "mean_attempts")]
                rows.append((f"s={s}", n, e, "members_wrong_before_repair", measures.pre_repair_errors(f)))
    return _rows(spark, rows)


def bucketing(spark: SparkSession, d: str, names: tuple[str, ...] = ("indeg_supplier", "indeg_part", "indeg_order")) -> DataFrame:
    """Seconds, bits and bucket loads of the bucketed sparse-linear filter."""
    rows = []
    for name in names:
        pairs, _ = written(globals()[name](spark, d), name)
        key = pairs.columns[0]
        f = build.build_bucketed_sparse(pairs, key, "value", k=12)
        n, buckets = f.n, f.spec.shards * f.spec.buckets
        load = measures.bucket_load(pairs, key, buckets, f.spec.seed) | {"hashes_tried": float(build.choose_bucket_seed(pairs, key, buckets)[2])}
        rows += [("bslf", n, buckets, what, x) for what, x in load.items()]
        rows += [("bslf", n, buckets, "kernel_seconds", measures.build_stats(f)["kernel_seconds"]), ("bslf", n, buckets, "bits_per_key", measures.size_bits(f)["per_key"])]
        if n <= 400:
            g = build.build_sparse_linear(pairs, key, "value", k=12)
            rows.append(("slf", n, 1, "kernel_seconds", measures.build_stats(g)["kernel_seconds"]))
    return _rows(spark, rows)


def hash_quality(spark: SparkSession, d: str, seeds: int = 10) -> DataFrame:
    """Draws on sequential keys for each hash family."""
    pairs, _ = written(indeg_part(spark, d), "pairs")
    rows = []
    for family in ("xx64", "md5", "two_universal"):
        draws = [measures.build_stats(build.build_acyclic(pairs, "l_partkey", "value", k=7, family=family, seed=s))["mean_attempts"] for s in range(1, seeds + 1)]
        rows.append((family, pairs.count(), "sequential", "draws", sum(draws) / len(draws)))
    return _rows(spark, rows)


def lookup_speed(spark: SparkSession, d: str, repeat: int = 20) -> DataFrame:
    """Rows a second of hits and of misses for the acyclic filter, its competitor, the dictionary and the bucketed filter."""
    pairs, _ = written(indeg_order(spark, d), "pairs")
    hits = pairs.select("l_orderkey").withColumn("r", F.explode(F.sequence(F.lit(1), F.lit(repeat)))).select("l_orderkey")
    misses = hits.select((F.col("l_orderkey") + 10**9).alias("l_orderkey"))
    made: dict[str, Filter] = {"acyclic": build.build_acyclic(pairs, "l_orderkey", "value", k=5), "matched": build.build_matched(pairs, "l_orderkey", "value", k=5), "dict": build.build_hash_dict(pairs, "l_orderkey", "value"), "bslf": build.build_bucketed_sparse(pairs, "l_orderkey", "value", k=5)}
    rows = []
    for m, f in made.items():
        for what, keys in (("hits", hits), ("misses", misses)):
            measures.measure_lookup(keys, f, "l_orderkey")
            rows.append((m, f.n, what, "rows_per_second", measures.measure_lookup(keys, f, "l_orderkey")["rows_per_second"]))
    return _rows(spark, rows)


def growth(spark: SparkSession, d: str) -> DataFrame:
    """(method, slope): the power of n by which kernel seconds grow, over key sets of the given tables."""
    rows = []
    for n in (50, 100, 200, 400):
        pairs = spark.range(1, n + 1).select(F.col("id").alias("key"), (F.col("id") % 32).alias("value"))
        rows.append(("sparse", n, "", "seconds", measures.build_stats(build.build_sparse_linear(pairs, "key", "value", k=5))["kernel_seconds"]))
    for n in (10_000, 40_000, 160_000):
        pairs = spark.range(1, n + 1).select(F.col("id").alias("key"), (F.col("id") % 32).alias("value"))
        for m, f in (("acyclic", build.build_acyclic(pairs, "key", "value", k=5, shards=1)), ("matched", build.build_matched(pairs, "key", "value", k=5, shards=1)), ("bslf", build.build_bucketed_sparse(pairs.where(F.col("key") <= n // 4), "key", "value", k=5))):
            stats = measures.build_stats(f)
            rows.append((m, f.n, "", "seconds", stats["kernel_seconds"] / (stats["mean_attempts"] if m != "bslf" else 1)))
    return measures.fit_slope(_rows(spark, rows), "n", "measured", "method")


def space(spark: SparkSession, d: str, k: int = 5) -> DataFrame:
    """Bits for each key over the error: by the formulas, and measured on the orders' in-degrees."""
    rows = [(m, 0, f"{e:.3e}", "bits_per_key", x) for m, e, x in measures.space_table(k, [2.0**-b for b in range(4, 33, 4)])]
    pairs, _ = written(indeg_order(spark, d), "pairs")
    some, _ = written(pairs.orderBy("l_orderkey").limit(400), "some")
    for bits in range(4, 33, 4):
        error = 2.0**-bits
        made = {
            "acyclic": build.build_acyclic(pairs, "l_orderkey", "value", k=k, error=error),
            "matched": build.build_matched(pairs, "l_orderkey", "value", k=k, error=error),
            "sparse": build.build_sparse_linear(some, "l_orderkey", "value", k=k, p_bits=k + bits + 1),
            "bslf": build.build_bucketed_sparse(pairs, "l_orderkey", "value", k=k, p_bits=k + bits + 1),
            "membership": build.build_membership(pairs, "l_orderkey", error=error),
            "dict_membership": build.build_dict_with_membership(pairs, "l_orderkey", "value", k=k, error=error),
        }
        rows += [(m, f.n, f"{error:.3e}", "measured_bits_per_key", measures.size_bits(f)["per_key"]) for m, f in made.items()]
    made = build.build_hash_dict(pairs, "l_orderkey", "value", k=k)
    return _rows(spark, [*rows, ("dict", made.n, f"{2.0**-64:.3e}", "measured_bits_per_key", measures.size_bits(made)["per_key"])])


def setup_loops(spark: SparkSession, d: str, sizes: tuple[int, ...] = (20, 50, 100, 400, 1_000, 4_000), seeds: int = 50) -> DataFrame:
    """Generators and primes drawn until two primes fit, for both ways to test a prime, and how many slots the first prime adds.

    The order keys are dealt to buckets of about each of the sizes, and each bucket draws for the keys that it got. Buckets of one size draw the same, so that is done once.
    """
    keys = table(spark, d, "orders").select("o_orderkey").where("o_orderkey is not null")
    total = keys.count()
    buckets = F.explode(F.array(*(F.struct(F.lit(m).alias("mean"), F.lit(max(1, round(total / m))).alias("of")) for m in sizes))).alias("b")
    dealt = keys.select("o_orderkey", buckets).groupBy("b.mean", F.pmod(F.xxhash64("o_orderkey", "b.mean"), F.col("b.of")).alias("bucket")).agg(F.count("*").alias("n"))
    each = dealt.groupBy("mean", "n").agg(F.count("*").alias("buckets"))

    def run(batches):
        for batch in batches:
            for mean, n, held in zip(*(batch.column(i).to_pylist() for i in range(3))):
                for method in ("direct", "list"):
                    drawn = [choose_primes(n, 0.1, 31, s, method) for s in range(1, seeds + 1)]
                    sums = [held * sum(x.generator_draws for x in drawn) / seeds, held * sum(x.prime_draws for x in drawn) / seeds, held * drawn[0].q / (1.1 * n)]
                    yield pa.RecordBatch.from_pylist([{"mean": mean, "method": method, "buckets": held, "generator_draws": sums[0], "prime_draws": sums[1], "slots_over_n_1_eps": sums[2]}])

    what = ("generator_draws", "prime_draws", "slots_over_n_1_eps")
    drawn = each.repartition("mean", "n").mapInArrow(run, "mean long, method string, buckets long, " + ", ".join(f"{w} double" for w in what))
    found = drawn.groupBy("mean", "method").agg(*(((F.sum(w) / F.sum("buckets")).alias(w)) for w in what)).orderBy("mean", "method").collect()  # a row for each size and method
    return _rows(spark, [(r["method"], r["mean"], "p_bits=31", w, r[w]) for r in found for w in what])


def full_rank(spark: SparkSession, d: str, trials: int = 100) -> DataFrame:
    """How often a random sparse matrix, its rows drawn from supplier keys, has full rank, against the proven lower bound: what a solver that takes all rows at once would have to count on."""
    keys, rows = table(spark, d, "supplier").select("s_suppkey"), []
    shapes = [(q, r, s, choose_primes(q, 0.01, 31, 7).p) for q, r in ((53, 40), (53, 48), (101, 80), (101, 90)) for s in (1, 2, 3, 4)]
    for (q, r, s, p), rate in measures.full_rank_rates(keys, "s_suppkey", shapes, trials).items():
        rows += [(f"s={s}", r, f"q={q}", "full_rank_share", rate), (f"s={s}", r, f"q={q}", "bound", algebra.full_rank_share_bound(q, s, r, p))]
    return _rows(spark, rows)


def lookup_counts(spark: SparkSession, d: str) -> DataFrame:
    """(metric, value): hashes and reads counted over looking up every supplier, as totals."""
    pairs, _ = written(indeg_supplier(spark, d), "pairs")
    key, rows = "l_suppkey", []
    made = {
        "acyclic": build.build_acyclic(pairs, key, "value", k=16),
        "acyclic sharded": build.build_acyclic(pairs, key, "value", k=16, shards=2),
        "matched r=2": build.build_matched(pairs, key, "value", k=16),
        "matched r=3": build.build_matched(pairs, key, "value", k=16, r=3, slots_factor=1.5),
        "peeled": build.build_peeled(pairs, key, "value", k=16),
        "bitmap": build.build_bitmap_map(pairs, key, "value", k=16),
    }
    for m, f in made.items():
        cost = measures.counted_cost(pairs, f, key)
        rows += [(f"{m} {what}", int(cost[what])) for what in ("hashes", "reads")]
    return spark.createDataFrame(rows, "metric string, value long")
