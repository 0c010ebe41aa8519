"""Builders, lookups, updates, baselines, measures, storage and streams on the given tables."""

import re
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from keyloom import queries as Q
from keyloom import workloads as W
from keyloom.functions import sqlapi
from keyloom.operators import build as B
from keyloom.operators import global_graph as G
from keyloom.operators import lookup as lookups
from keyloom.operators import measures as M
from keyloom.operators import relational as R
from keyloom.operators.kernels import BuildError
from keyloom.operators.lookup import lookup, lookup_packed, packed
from keyloom.operators.mutable import edges, rejected, update_matched, update_values
from keyloom.plans import store
from keyloom.plans.scratch import remove, written
from keyloom.sources.datasource import SlotSource
from keyloom.sources.tables import read_pairs, write_pairs
from keyloom.streaming import streams as S


@pytest.fixture(scope="module")
def orders(spark, small):
    return written(W.indeg_order(spark, small), "orders")[0]


@pytest.fixture(scope="module")
def absent(spark):
    return spark.range(20_000).select((F.col("id") + 10**9).alias("l_orderkey"))


BUILDERS = {
    "acyclic": lambda p, **o: B.build_acyclic(p, "l_orderkey", "value", k=5, **o),
    "independent": lambda p, **o: B.build_acyclic(p, "l_orderkey", "value", k=5, endpoints="independent", **o),
    "mutable": lambda p, **o: B.build_mutable(p, "l_orderkey", "value", k=5, **o),
    "matched2": lambda p, **o: B.build_matched(p, "l_orderkey", "value", k=5, **o),
    "matched3": lambda p, **o: B.build_matched(p, "l_orderkey", "value", k=5, r=3, slots_factor=1.5, **o),
    "peeled": lambda p, **o: B.build_peeled(p, "l_orderkey", "value", k=5, **o),
    "xor": lambda p, **o: B.build_xor_sparse(p, "l_orderkey", "value", k=5, **o),
    "bslf": lambda p: B.build_bucketed_sparse(p, "l_orderkey", "value", k=5),
    "bslf61": lambda p: B.build_bucketed_sparse(p, "l_orderkey", "value", k=5, p_bits=61),
    "dict": lambda p: B.build_hash_dict(p, "l_orderkey", "value"),
    "low_collision": lambda p: B.build_low_collision_dict(p, "l_orderkey", "value"),
    "dict_membership": lambda p: B.build_dict_with_membership(p, "l_orderkey", "value"),
    "raw": lambda p: B.build_bitmap_map(p, "l_orderkey", "value", k=5),
}


@pytest.mark.parametrize("name", BUILDERS)
def test_members_are_exact(name, orders):
    assert M.member_mismatches(orders, BUILDERS[name](orders), "l_orderkey", "value") == 0


@pytest.mark.parametrize("name", ["acyclic", "matched2", "xor", "peeled"])
@pytest.mark.parametrize("bits", [2, 5])
def test_error_on_absent_keys(name, bits, orders, absent):
    found = M.false_value_rate(BUILDERS[name](orders, error=2.0**-bits), absent, "l_orderkey")
    assert abs(found["sigmas"]) < 5, found


@pytest.mark.parametrize("name", ["dict", "dict_membership", "bslf"])
def test_rare_errors(name, orders, absent):
    assert M.false_value_rate(BUILDERS[name](orders), absent, "l_orderkey")["hits"] == 0


def test_membership(orders, absent):
    f = B.build_membership(orders, "l_orderkey", error=2.0**-5)
    assert lookup(orders, f, "l_orderkey", "m").where("m is null").isEmpty()
    assert M.false_value_rate(f, absent, "l_orderkey")["rate"] < 2 * 2.0**-5


@pytest.mark.parametrize("n", [0, 1, 2])
@pytest.mark.parametrize("name", ["acyclic", "mutable", "matched2", "dict", "bslf", "xor", "peeled"])
def test_few_keys(name, n, spark):
    p = spark.range(n).select(F.col("id").alias("l_orderkey"), (F.col("id") + 3).alias("value"))
    f = BUILDERS[name](p)
    probe = spark.range(-2, 5).select(F.col("id").alias("l_orderkey"))
    got = {r["l_orderkey"]: r["value"] for r in lookup(probe, f, "l_orderkey").collect()}
    assert got == {i: i + 3 if 0 <= i < n else None for i in range(-2, 5)}


def test_bad_input(spark):
    rows = lambda *r: spark.createDataFrame(list(r), "key long, value long")
    for df in (rows((None, 1), (2, 1)), rows((1, 2), (1, 2)), rows((1, 2), (1, 3)), rows((1, 40)), rows((1, -1)), rows((1, None))):
        with pytest.raises(Exception, match="BuildError|NULL|repeated|conflicting|fit"):
            B.build_acyclic(df, "key", "value", k=5)
    one = rows((1, 1))
    for bad in (lambda: B.build_acyclic(one, "key", "value", c=2.0), lambda: B.build_matched(one, "key", "value", r=1), lambda: B.build_sparse_linear(one, "key", "value", k=5, s=1), lambda: B.build_sparse_linear(one, "key", "value", k=9, p_bits=9), lambda: B.build_acyclic(one, "key", "value", k=5, modulus=31), lambda: B.build_sparse_linear(spark.range(20).select("id", "id"), "id", "id", k=5, limit=10)):
        with pytest.raises(ValueError):
            bad()
    with pytest.raises(TypeError):
        B.build_acyclic(spark.createDataFrame([(1.5, 1)], "key double, value long"), "key", "value")


def test_conflict_rules(spark):
    rows = spark.createDataFrame([(1, 2), (1, 3), (2, 5)], "key long, value long")
    assert {r["key"]: r["value"] for r in R.check_function(rows, "key", "value", 5, "max").collect()} == {1: 3, 2: 5}
    with pytest.raises(Exception, match="two values"):
        R.check_function(rows, "key", "value", 5).collect()


def test_keys_of_many_kinds(spark):
    rows = spark.createDataFrame([(2**63 - 1, "", True), (-(2**63), "é" * 1000, False), (0, "x", None)], "a long, b string, c boolean").withColumn("value", F.lit(7))
    f = B.build_acyclic(rows.where("c is not null"), ["a", "b", "c"], "value", k=3)
    assert [r["v"] for r in lookup(rows, f, ["a", "b", "c"], "v").orderBy("a").collect()] == [7, None, 7]
    nation = spark.createDataFrame([(1, 4)], "k int, value long")
    assert lookup(spark.createDataFrame([(1,), (2,), (None,)], "k long"), B.build_acyclic(nation, "k", "value", k=3), "k", "v").orderBy(F.col("k").asc_nulls_first()).select("v").collect() == [(None,), (4,), (None,)]


def test_same_bytes_whatever_the_partitioning(orders):
    sums = {store.checksum(B.build_acyclic(df, "l_orderkey", "value", k=5, shards=3).tables) for df in (orders, orders.repartition(9), orders.orderBy(F.desc("l_orderkey")))}
    assert len(sums) == 1


def test_strategies_and_plans(orders):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5, shards=4)
    for strategy in ("broadcast", "shuffle_hash", "merge"):
        assert R.compare(orders, f, orders, "l_orderkey", "value").isEmpty()
        lookup(orders, f, "l_orderkey", "v", strategy).collect()
    plan = lookup(orders.select("l_orderkey"), f, "l_orderkey", "v", "broadcast")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Exchange hashpartitioning" not in plan and "Python" not in plan


def test_one_graph_equals_one_shard(spark, small):
    pairs = written(W.indeg_part(spark, small), "parts")[0]
    one = B.build_acyclic(pairs, "l_partkey", "value", k=7, shards=1, canonical=True)
    whole = G.build_acyclic_global(pairs, "l_partkey", "value", k=7)
    front = G.build_acyclic_global(pairs, "l_partkey", "value", k=7, solve="frontier")
    g = one.tables.first()["g"]
    assert one.tables.first()["seed"] == whole.seed
    for other in (whole, front):
        cells = {r["slot"]: r["g"] for r in other.slots.collect()}
        assert all(g[s] == v for s, v in cells.items()) and all(g[s] == 0 for s in range(len(g)) if s not in cells)


@pytest.mark.parametrize("mode", ["recompute", "shift"])
def test_updates_touch_their_trees_only(mode, spark, orders):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5, shards=2)
    graph = written(edges(f, orders, "l_orderkey", "value"), "graph")[0]
    new = W.changes(orders, "l_orderkey", 50)
    changed, graph2, deltas = update_values(f, graph, new, "l_orderkey", mode=mode)
    truth = orders.join(new.withColumnRenamed("value", "w"), "l_orderkey", "left").select("l_orderkey", F.coalesce("w", "value").alias("value"))
    assert M.member_mismatches(truth, changed, "l_orderkey", "value") == 0
    cells = {(r["shard"], r["slot"]) for r in deltas.collect()}
    before, after = ({r["shard"]: r["g"] for r in x.tables.collect()} for x in (f, changed))
    assert all(before[s][i] == after[s][i] or (s, i) in cells for s in before for i in range(len(before[s])))
    assert len(cells) <= new.count() * M.build_stats(f)["max_component"]
    if mode == "recompute":
        fresh = B.build_mutable(truth, "l_orderkey", "value", k=5, shards=2)
        assert store.checksum(fresh.tables) == store.checksum(changed.tables)
    again, _, _ = update_values(changed, graph2, new, "l_orderkey", mode=mode)
    assert store.checksum(again.tables) == store.checksum(changed.tables)
    strange = spark.createDataFrame([(10**10, 3)], "l_orderkey long, value long")
    assert rejected(f, graph, strange, "l_orderkey").count() == 1
    with pytest.raises(Exception, match="fit"):
        update_values(f, graph, orders.limit(1).withColumn("value", F.lit(99)), "l_orderkey")


@pytest.mark.parametrize("mode", ["recompute", "shift"])
def test_doubled_tied_and_null_changes(mode, spark, orders):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5, shards=3)
    graph = written(edges(f, orders, "l_orderkey", "value"), "graph")[0]
    some = orders.where("l_orderkey % 9 = 0").select("l_orderkey", ((F.col("value") + 1) % 17).alias("value"))
    update = lambda rows, **o: update_values(f, graph, rows, "l_orderkey", mode=mode, **o)
    truth = orders.join(some.withColumnRenamed("value", "w"), "l_orderkey", "left").select("l_orderkey", F.coalesce("w", "value").alias("value"))
    for rows in (some.unionByName(some), some.unionByName(spark.createDataFrame([(None, 3), (10**10, 3)], "l_orderkey long, value long"))):
        changed, after, _ = update(rows)
        assert M.member_mismatches(truth, changed, "l_orderkey", "value") == 0 and after.count() == graph.count()
    other = some.withColumn("value", (F.col("value") + 5) % 17)
    with pytest.raises(Exception, match="two new values"):
        update(some.unionByName(other))
    with pytest.raises(Exception, match="NULL"):
        update(some.withColumn("value", F.lit(None).cast("long")))
    dated = other.withColumn("at", F.lit(1)).unionByName(some.withColumn("at", F.lit(2))).unionByName(other.withColumn("at", F.lit(None).cast("int")))
    assert M.member_mismatches(truth, update(dated, order="at")[0], "l_orderkey", "value") == 0
    assert M.member_mismatches(truth, update(dated.unionByName(some.withColumn("at", F.lit(2))), order="at")[0], "l_orderkey", "value") == 0
    with pytest.raises(Exception, match="two new values"):
        update(dated.unionByName(other.withColumn("at", F.lit(2))), order="at")


def test_updates_leave_other_shards_in_their_files(spark, orders):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5, shards=12)
    graph = written(edges(f, orders, "l_orderkey", "value"), "graph")[0]
    truth = {r["l_orderkey"]: r["value"] for r in orders.collect()}
    for step, key in enumerate(sorted(truth)[:10]):
        truth[key] = (truth[key] + 3 + step) % 17
        f, graph, deltas = update_values(f, graph, spark.createDataFrame([(key, truth[key])], "l_orderkey long, value long"), "l_orderkey")
        assert deltas.select("shard").distinct().count() == 1
    assert graph.count() == len(truth) and f.tables.count() == 12
    now = spark.createDataFrame(list(truth.items()), "l_orderkey long, value long")
    assert M.member_mismatches(now, f, "l_orderkey", "value") == 0
    same, _, none = update_values(f, graph, now.limit(0), "l_orderkey")
    assert same is f and none.isEmpty()


def test_component_cap(orders):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5, c=3.0, component_cap=40, shards=2)
    assert M.build_stats(f)["max_component"] <= 40


def test_matched_update_is_one_cell(orders):
    f = B.build_matched(orders, "l_orderkey", "value", k=5)
    new = W.changes(orders, "l_orderkey", 10)
    changed, cells = update_matched(f, new, "l_orderkey")
    assert cells.count() == new.count() and M.member_mismatches(new, changed, "l_orderkey", "value") == 0


def test_repair_of_a_tiny_field(spark):
    pairs = spark.range(20).select("id", (F.col("id") % 4).alias("value"))
    f = B.build_sparse_linear(pairs, "id", "value", k=2, p_bits=4, s=2, eps=0.1)
    assert M.member_mismatches(pairs, f, "id", "value") == 0


def test_sparse_space_and_blocks(spark, small):
    pairs = written(W.indeg_part(spark, small), "parts")[0]
    tries = {s: M.build_stats(B.build_sparse_linear(pairs, "l_partkey", "value", k=7, eps=0.05, s=s, allow_s1=True, max_blocks=3000))["max_blocks"] for s in (1, 2, 3)}
    assert tries[1] > tries[2] >= tries[3]
    assert M.build_stats(B.build_sparse_linear(pairs, "l_partkey", "value", k=7, field="any_prime"))["n"] == 200


def test_bucket_loads(orders):
    buckets = B.bucket_count(orders.count())
    seed, most, _ = B.choose_bucket_seed(orders, "l_orderkey", buckets)
    load = M.bucket_load(orders, "l_orderkey", buckets, seed)
    assert load["max"] == most < 5.5 * load["mean"] and load["above"] == 0


def test_space_formulas(orders):
    n = orders.count()
    for name in ("acyclic", "matched2"):
        f = BUILDERS[name](orders)
        assert M.size_bits(f)["table"] == pytest.approx(M.predicted_bits(f.spec, n), rel=0.01)
    f = BUILDERS["acyclic"](orders)
    row = packed(f).first()
    assert len(row["g"]) == -(-row["n_slots"] * 37 // 8)
    assert M.size_bits(f)["per_key"] == pytest.approx(92.5, abs=0.2)


def test_save_load_register(spark, orders, tmp_path):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5, shards=3)
    store.save(f, f"{tmp_path}/f", groups=2)
    g = store.load(spark, f"{tmp_path}/f")
    assert store.checksum(g.tables) == store.checksum(f.tables) and g.get(1) == f.get(1)
    spark.dataSource.register(SlotSource)
    rows = spark.read.format("keyloom_slots").option("path", f"{tmp_path}/f").load()
    assert rows.count() == f.tables.agg(F.sum("n_slots")).first()[0]
    sqlapi.register_lookup(spark, "vf_lookup", f)
    orders.createOrReplaceTempView("pairs")
    assert spark.sql("select count(*) from pairs where not (vf_lookup(l_orderkey) <=> value)").first()[0] == 0
    assert spark.sql("select vf_lookup(cast(null as bigint)), vf_lookup(-7)").first() == (None, None)
    sqlapi.register_functions(spark)
    assert spark.sql("select count(*) from vf_params(1000, 5, 0.001D)").first()[0] == 5
    assert 0 <= spark.sql("select vf_slot(1, 2, 3, 100)").first()[0] < 100


@pytest.mark.parametrize("fmt", ["parquet", "orc", "csv", "json"])
def test_pair_files(fmt, spark, orders, tmp_path):
    write_pairs(orders, f"{tmp_path}/{fmt}", fmt)
    back = read_pairs(spark, f"{tmp_path}/{fmt}", fmt, "l_orderkey long, value long")
    assert back.exceptAll(orders).isEmpty() and back.count() == orders.count()


def test_stream_of_updates(spark, orders, tmp_path):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5)
    feed = S.UpdateFeed(f, edges(f, orders, "l_orderkey", "value"), "l_orderkey")
    new = W.changes(orders, "l_orderkey", 20)
    new.coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(new.schema).parquet(f"{tmp_path}/in")
    S.apply_updates(stream, feed, f"{tmp_path}/check")
    assert M.member_mismatches(new, feed.filter, "l_orderkey", "value") == 0
    version = feed.filter.version
    feed(new, feed.last_batch)
    assert feed.filter.version == version


def test_a_feed_goes_on_from_its_last_state(spark, orders, tmp_path):
    f = B.build_mutable(orders, "l_orderkey", "value", k=5)
    feed = S.UpdateFeed(f, edges(f, orders, "l_orderkey", "value"), "l_orderkey", path=f"{tmp_path}/states")
    first, second = W.changes(orders, "l_orderkey", 20), W.changes(orders, "l_orderkey", 7).withColumn("value", F.lit(3).cast("long"))
    feed(first, 0)
    feed(second, 1)
    back = S.UpdateFeed.resume(spark, f"{tmp_path}/states", "l_orderkey")
    assert back.last_batch == 1 and M.member_mismatches(second, back.filter, "l_orderkey", "value") == 0
    back(first, 1)  # again
    assert M.member_mismatches(second, back.filter, "l_orderkey", "value") == 0
    back(first, 2)
    assert M.member_mismatches(first, back.filter, "l_orderkey", "value") == 0


def test_one_graph_is_solved_in_tasks_of_many_trees(spark, small, monkeypatch):
    pairs = written(W.indeg_part(spark, small), "parts")[0]
    whole = B.build_acyclic(pairs, "l_partkey", "value", k=7, canonical=True, shards=1).tables.first()
    for size in (1, 30, 1 << 16):
        monkeypatch.setattr(G, "EDGES_A_TASK", size)
        made = G.build_acyclic_global(pairs, "l_partkey", "value", k=7)
        assert all(whole["g"][r["slot"]] == r["g"] for r in made.slots.collect())
    edges_, trees = spark.createDataFrame([(0, 1, 5), (2, 3, 6)], "u long, v long, rhs long"), spark.createDataFrame([(i, i // 2 * 2) for i in range(4)], "slot long, component long")
    solved = G._by_component(edges_, trees, 8, 2)
    assert {r["slot"]: r["g"] for r in solved.collect()} == {0: 0, 1: 5, 2: 0, 3: 6} and "[component" not in solved._jdf.queryExecution().toString().split("FlatMapGroupsInArrow")[1].split("\n")[0]


@pytest.fixture(scope="module")
def many_suppliers(spark, tmp_path_factory):
    """Tables with 4,500 suppliers, 300 of them without lines."""
    d = str(tmp_path_factory.mktemp("suppliers"))
    spark.range(4_500).select(F.col("id").alias("s_suppkey")).write.parquet(f"{d}/supplier.parquet")
    spark.range(9_000).select((F.col("id") % 4_200).alias("l_suppkey")).write.parquet(f"{d}/lineitem.parquet")
    return d


def suppliers_of(spark, d, name):
    rows = {r["s_suppkey"]: r["value"] for r in Q.QUERIES[name](spark, d).collect()}
    return rows == {i: None if i >= 4_200 else 3 if i < 600 else 2 for i in range(4_500)}


def test_sparse_filter_of_many_keys_any_prime(spark, many_suppliers):
    assert suppliers_of(spark, many_suppliers, "slf_any_prime")


def test_sparse_filter_of_many_keys_p61(spark, many_suppliers):
    assert suppliers_of(spark, many_suppliers, "slf_p61")


def test_sparse_filter_of_many_keys_s2(spark, many_suppliers):
    assert suppliers_of(spark, many_suppliers, "slf_s2")


def test_sparse_filter_of_many_keys_s3(spark, many_suppliers):
    assert suppliers_of(spark, many_suppliers, "slf_s3")


def test_sparse_filter_of_many_keys_s4(spark, many_suppliers):
    assert suppliers_of(spark, many_suppliers, "slf_s4")


@pytest.fixture(scope="module", params=[20, 1_200])
def odd_suppliers(spark, tmp_path_factory, request):
    """So many suppliers, the first with 70,000 lines, the last without any; lines and a supplier without a key."""
    n, d = request.param, str(tmp_path_factory.mktemp("odd"))
    spark.range(n + 1).select(F.when(F.col("id") < n, F.col("id")).alias("s_suppkey")).write.parquet(f"{d}/supplier.parquet")
    lines = spark.range(70_000).select(F.lit(0).cast("long").alias("l_suppkey")).union(spark.range(1, n - 1)).union(spark.range(5).select(F.lit(None).cast("long")))
    lines.write.parquet(f"{d}/lineitem.parquet")
    return d, {None: None, 0: 70_000, n - 1: None} | {i: 1 for i in range(1, n - 1)}


@pytest.mark.parametrize("name", ["slf_s2", "slf_s3", "slf_s4"])
def test_sparse_filter_of_null_keys_and_large_values(spark, odd_suppliers, name):
    d, expected = odd_suppliers
    rows = Q.QUERIES[name](spark, d).collect()
    assert len(rows) == len(expected) and {r["s_suppkey"]: r["value"] for r in rows} == expected


def test_sparse_filter_of_parts_gives_absent_parts_no_value(spark, small, tmp_path):
    absent = 1_405_434  # among 200 parts of this table and the query's own prime, this key's equation gives 711
    f = B.build_sparse_linear(W.indeg_part(spark, small).orderBy("l_partkey").limit(200), "l_partkey", "value", k=10)
    key = spark.createDataFrame([(absent,)], "p_partkey long")
    assert lookup(key, f, "p_partkey").first()["value"] == 711
    parts = spark.read.parquet(f"{small}/part.parquet").select("p_partkey")
    parts.unionByName(key).write.parquet(f"{tmp_path}/part.parquet")
    spark.read.parquet(f"{small}/lineitem.parquet").write.parquet(f"{tmp_path}/lineitem.parquet")
    rows = Q.QUERIES["slf_parts"](spark, str(tmp_path))
    assert rows.where(f"p_partkey = {absent} and value is null").count() == 1 and rows.where("value is not null").count() == 200


@pytest.mark.parametrize("n", [300, 4_500])
def test_sparse_filter_of_parts_takes_all_parts(spark, tmp_path, n):
    spark.range(n + 7).select(F.col("id").alias("p_partkey")).write.parquet(f"{tmp_path}/part.parquet")
    spark.range(3 * n).select((F.col("id") % n).alias("l_partkey")).union(spark.range(2_000).select(F.lit(n - 1).cast("long"))).write.parquet(f"{tmp_path}/lineitem.parquet")
    rows = {r["p_partkey"]: r["value"] for r in Q.QUERIES["slf_parts"](spark, str(tmp_path)).collect()}
    assert rows == {i: 3 for i in range(n - 1)} | {n - 1: 2_003} | {i: None for i in range(n, n + 7)}


def test_two_universal_gives_absent_orders_no_value(spark, tmp_path):
    spark.range(100).select(F.explode(F.array(F.col("id"), F.col("id") + (1 << 31) - 1)).alias("o_orderkey")).write.parquet(f"{tmp_path}/orders.parquet")
    spark.range(300).select((F.col("id") % 100).alias("l_orderkey")).write.parquet(f"{tmp_path}/lineitem.parquet")
    rows = Q.QUERIES["af_two_universal"](spark, str(tmp_path))
    assert {r["o_orderkey"]: r["value"] for r in rows.collect()} == {i: 3 for i in range(100)} | {i + (1 << 31) - 1: None for i in range(100)}


@pytest.fixture(scope="module")
def popular_url(spark, tmp_path_factory):
    """1,100 pages that all link to one URL."""
    d = str(tmp_path_factory.mktemp("pages"))
    html = F.lit('<a href="http://a.example/x">x</a>')
    spark.range(1_100).select(F.col("id").alias("page_id"), F.format_string("http://b.example/%d", "id").alias("url"), html.alias("html")).write.parquet(f"{d}/pages.parquet")
    return d


def test_indegree_of_a_popular_url(spark, popular_url):
    rows = Q.QUERIES["indeg_url"](spark, popular_url)
    assert rows.count() == 1_101 and [r["value"] for r in rows.where("value is not null").collect()] == [1_100]


def test_creation_over_a_popular_url(spark, popular_url):
    rows = W.creation(spark, popular_url, trials=1, names=("indeg_url",))
    assert {r["method"] for r in rows.collect()} == {"acyclic", "acyclic_independent", "matched", "matched_peel"}


@pytest.mark.parametrize("name", ["slf_p61", "slf_s2", "slf_s3", "slf_s4"])
def test_key_set_whose_files_are_gone_is_made_anew(spark, small, name):
    Q.QUERIES["slf_any_prime"](spark, small)
    remove(spark, Q.pairs_of(spark, small, "indeg_supplier").inputFiles()[0].rpartition("/")[0])
    assert Q.QUERIES[name](spark, small).count() == spark.read.parquet(f"{small}/supplier.parquet").count()


@pytest.fixture(scope="module")
def few_rows(spark, tmp_path_factory):
    """Lines whose entries are known, and 300 orders and suppliers."""
    d = str(tmp_path_factory.mktemp("few"))
    lines = [(1, 0, 0, 0, 0.0), (1, 1, 1, 1, 1.0), (1, 1, 0, 0, 0.0), (2, 1, 0, 0, 0.0)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double").write.parquet(f"{d}/lineitem.parquet")
    spark.range(300).select(F.col("id").alias("o_orderkey")).write.parquet(f"{d}/orders.parquet")
    spark.range(300).select(F.col("id").alias("s_suppkey")).write.parquet(f"{d}/supplier.parquet")
    return d


def rows_of(spark, d, name, *columns):
    return {tuple(r[c] for c in columns) for r in Q.QUERIES[name](spark, d).collect()}


def test_circulants_of_lines(spark, few_rows):
    assert rows_of(spark, few_rows, "circulant_rank", "q", "p", "n") == {(5, 2, 2), (5, 3, 2), (3, 5, 3)}


def test_full_rank_of_supplier_keys(spark, few_rows):
    p = 2**31 - 1
    found = M.full_rank_rates(spark.read.parquet(f"{few_rows}/supplier.parquet"), "s_suppkey", [(11, 3, 3, p), (5, 6, 3, p)], 40)
    assert found[11, 3, 3, p] > 0.9 and found[5, 6, 3, p] == 0.0


def test_nonzero_sums_of_lines(spark, few_rows):
    assert {r for r in rows_of(spark, few_rows, "nonzero_sum_counts", "p", "s", "n", "patterns", "possible") if r[0] == 3} == {(3, 1, 4, 2, 2), (3, 2, 2, 1, 2), (3, 3, 0, 0, 6)}


def test_nonzero_sums_read_the_lines_themselves(spark, few_rows):
    for _ in range(2):  # not a table that an earlier call left
        files = Q.QUERIES["nonzero_sum_counts"](spark, few_rows).inputFiles()
        assert files and all("/lineitem.parquet/" in f for f in files)


def test_generators_among_order_keys(spark, few_rows):
    assert {r for r in rows_of(spark, few_rows, "primitive_roots", "q", "a", "n") if r[0] == 5} == {(5, 2, 60), (5, 3, 60)}


def test_prime_draws_of_buckets(spark, few_rows):
    rows = W.setup_loops(spark, few_rows, sizes=(20, 100), seeds=3).collect()
    assert {(r["method"], r["n"]) for r in rows} == {(m, n) for m in ("direct", "list") for n in (20, 100)} and all(r["measured"] > 0 for r in rows if r["measure"] != "generator_draws")


def test_sparse_vectors_of_lines(spark, few_rows):
    assert rows_of(spark, few_rows, "sparse_counts", "s", "n", "patterns", "possible") == {(0, 0, 0, 1), (1, 1, 1, 10), (2, 2, 2, 40), (3, 0, 0, 80), (4, 0, 0, 80), (5, 1, 1, 32)}


def test_graphs_of_order_keys(spark, few_rows):
    found = M.acyclic_rates(spark.read.parquet(f"{few_rows}/orders.parquet"), "o_orderkey", 250, (2.5,), 200)
    assert all(abs(stats["rate"] - stats["formula"]) < 0.15 for stats in found.values()) and len(found) == 2


def test_streams(spark, small, tmp_path):
    path = f"{small}/events.parquet"
    events = spark.read.parquet(path)
    members = B.build_membership(events.where("user_id < 8").select("user_id"), "user_id")
    new = S.run_once(S.pending_keys(S.events_stream(spark, path), members, "user_id").select("user_id"), "pending", f"{tmp_path}/a", "append")
    assert new.where("user_id < 8").isEmpty() and new.count() > 0
    pairs = S.run_once(S.interval_join(S.events_stream(spark, path).where("event_type = 'click'").select("user_id", "ts"), S.events_stream(spark, path).where("event_type = 'error'").select("user_id", "ts"), "user_id").select("user_id"), "pairs_joined", f"{tmp_path}/b", "append")
    assert pairs.count() >= 0
    assert S.late_report([{"stateOperators": [{"numRowsDroppedByWatermark": 3}]}, {}]) == 3


def test_stream_rows_are_written_by_executors(spark, small, tmp_path):
    rows = Q.QUERIES["stream_enrich"](spark, small)
    assert all(Q.QUERIES[q](spark, small).inputFiles() for q in ("stream_session", "stream_sliding"))
    assert rows.inputFiles() and rows.count() == spark.read.parquet(f"{small}/events.parquet").count()  # a table in memory has no files
    events = spark.read.parquet(f"{small}/events.parquet")
    events.repartition(2).write.parquet(f"{tmp_path}/events.parquet")
    for mode in ("append", "complete", "update"):  # a table of several files, one micro-batch each
        stream = S.events_stream(spark, f"{tmp_path}/events.parquet", per_trigger=1)
        got = S.run_once(stream if mode == "append" else stream.groupBy("user_id").count(), f"parts_{mode}", f"{tmp_path}/{mode}", mode)
        whole = events.groupBy("user_id").count()
        assert got.count() == events.count() if mode == "append" else got.exceptAll(whole).isEmpty() == (mode == "complete") and whole.subtract(got).isEmpty()


def state_files(spark, d, name):
    """Kinds of files in the state of a query's stream: .delta, where a map in the heap holds it."""
    checkpoint = Q.QUERIES[name](spark, d).inputFiles()[0].partition("-rows/")[0].removeprefix("file://")
    return {f.suffix for f in Path(checkpoint, "state").glob("*/[0-9]*/*") if not f.name.startswith(".")}


def test_state_of_sessions_is_in_files(spark, small):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    kinds = state_files(spark, small, "stream_session")
    assert kinds and ".delta" not in kinds
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass") == before


def test_state_of_sliding_windows_is_in_files(spark, small):
    kinds = state_files(spark, small, "stream_sliding")
    assert kinds and ".delta" not in kinds


def test_sliding_windows_are_made_of_counts_that_are_held_once(spark, small):
    made = Q.QUERIES["stream_sliding"](spark, small)
    held = spark.read.parquet(*{f.rpartition("/")[0] for f in made.inputFiles()})
    events = spark.read.parquet(f"{small}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    assert held.count() == events.groupBy("user_id", F.window("ts", "6 hours")).count().count() < made.count()
    some = events.union(events.limit(1).withColumn("user_id", F.lit(None).cast("long")))
    for window, slide in (("1 day", "6 hours"), ("3 hours", "1 hour"), ("1 hour", "1 hour")):
        whole = S.indegree(some, "user_id", window, slide)
        got = S.sliding(S.indegree(some, "user_id", slide), "user_id", window, slide)
        assert got.count() == whole.count() and got.exceptAll(whole).isEmpty()
    with pytest.raises(ValueError):
        S.sliding(events, "user_id", "1 day", "7 hours")


def test_asof_and_bands(spark):
    events = spark.createDataFrame([(1, 5, "a"), (1, 10, "b"), (2, 1, "c")], "key int, ts int, what string")
    versions = spark.createDataFrame([(1, 5, 50), (1, 7, 70), (2, 2, 20)], "key int, ts int, value int")
    assert {r["what"]: r["value_asof"] for r in R.asof_value(events, versions, "key").collect()} == {"a": 50, "b": 70, "c": None}


def test_blocks_are_tried_without_copies_of_slots(spark, orders, monkeypatch):
    f = B.build_bucketed_sparse(orders, "l_orderkey", "value", k=5)
    assert f.blocks() > 2
    probe = orders.select("l_orderkey").union(orders.select(F.col("l_orderkey") + 10**9)).union(spark.createDataFrame([(None,)], "l_orderkey long"))
    looked = lookup(probe, f, "l_orderkey")
    assert "lambda" not in looked._jdf.queryExecution().toString()  # a loop has no generated code: rows come to it with copies of all slots of their shard
    rows = {(r["l_orderkey"], r["value"]) for r in looked.collect()}
    monkeypatch.setattr(lookups, "INLINE_BLOCKS", 1)
    looped = lookup(probe, f, "l_orderkey")
    assert "lambda" in looped._jdf.queryExecution().toString() and rows == {(r["l_orderkey"], r["value"]) for r in looped.collect()}
    own = {(r["l_orderkey"], r["value"]) for r in orders.collect()}
    assert own <= rows and all(x is None for _, x in rows - own)


def test_measures(spark, orders):
    rows = spark.createDataFrame([("a", 10, 1.0), ("a", 100, 10.0), ("b", 10, 1.0), ("b", 100, 1000.0)], "method string, n long, measured double")
    slopes = {r["method"]: r["slope"] for r in M.fit_slope(rows, "n", "measured", "method").collect()}
    assert slopes["a"] == pytest.approx(1) and slopes["b"] == pytest.approx(3)
    assert M.report(rows).count() == 9 and M.report(rows, "rollup").count() == 7 and M.report(rows, "pivot").count() == 2
    stats = M.measure_build(lambda s: B.build_acyclic(orders, "l_orderkey", "value", k=5, seed=s), trials=2)
    assert stats["draws"] >= 1 and M.speedup({"kernel_seconds": 2.0}, {"kernel_seconds": 1.0}) == 2
    assert M.measure_lookup(orders, B.build_acyclic(orders, "l_orderkey", "value", k=5), "l_orderkey")["hits"] == orders.count()


def test_packed_lookup_of_nulls_and_absents(spark, orders):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5, shards=3)
    probe = spark.createDataFrame([(1,), (None,), (10**9,)], "l_orderkey long")
    got = {r["l_orderkey"]: r["value"] for r in lookup_packed(probe, f, "l_orderkey").collect()}
    assert got == {1: f.get(1), None: None, 10**9: None}


def test_names_that_clash(spark, orders):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5, shards=3)
    probe = orders.select(F.col("l_orderkey").alias("d0"), F.lit(1).alias("d1"), F.lit("x").alias("_shard"), F.lit(2).alias("_known"), F.lit(3).alias("_t_g"), F.col("value").alias("n_slots"))
    for look in (lookup, lookup_packed, lambda *a: lookup(*a, strategy="merge")):
        rows = look(probe, f, "d0", "out")
        assert rows.columns == [*probe.columns, "out"] and rows.where("not (out <=> n_slots) or d1 <> 1 or _t_g <> 3").isEmpty() and rows.count() == orders.count()


def test_null_keys_are_spread(spark, orders):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5, shards=2)
    probe = spark.range(2_000).select(F.when(F.col("id") < 5, F.col("id")).alias("l_orderkey"), "id")
    for rows in (lookup(probe, f, "l_orderkey", strategy="merge"), lookup_packed(probe, f, "l_orderkey")):
        assert rows.count() == 2_000 and rows.where("id >= 5 and value is not null").isEmpty()


def test_packed_composite_keys_and_hot_shards(spark, small, monkeypatch):
    from keyloom.operators import lookup as L

    monkeypatch.setattr(L, "PACKED_PROBES", 700)
    pairs = written(W.line_qty(spark, small), "lines")[0]
    f = B.build_acyclic(pairs, W.LINE_KEYS, "value", k=6, shards=2)
    probe = pairs.select("value", *W.LINE_KEYS).unionByName(pairs.select((-F.col("value")).alias("value"), *W.LINE_KEYS[:3], (F.col("l_linenumber") + 100).alias("l_linenumber")))
    rows = L.lookup_packed(probe, f, W.LINE_KEYS, "looked")
    assert rows.columns == [*probe.columns, "looked"] and rows.count() == 2 * pairs.count()
    assert rows.where("not (looked <=> if(value > 0, value, null))").isEmpty()


def test_broadcasts_are_refused_above_their_limit(orders, monkeypatch):
    from keyloom.operators import lookup as L

    f = B.build_acyclic(orders, "l_orderkey", "value", k=5)
    monkeypatch.setattr(L, "BROADCAST_BYTES", 100)
    with pytest.raises(ValueError, match="more than"):
        lookup(orders, f, "l_orderkey", strategy="broadcast")
    assert M.member_mismatches(orders, f, "l_orderkey", "value") == 0  # auto joins by shard


def test_counted_costs(orders):
    n = orders.count()
    for name, hashes, reads in (("acyclic", 3, 2), ("matched2", 3, 3), ("peeled", 4, 3)):
        assert M.counted_cost(orders, BUILDERS[name](orders), "l_orderkey") == {"keys": n, "hashes": hashes * n, "reads": reads * n}
    f = BUILDERS["bslf"](orders)
    cost = M.counted_cost(orders, f, "l_orderkey")
    tries = M.build_stats(f)["mean_tries"]
    assert cost["reads"] == pytest.approx(3 * tries * n) and cost["hashes"] == pytest.approx((2 + 6 * tries) * n)


def test_wide_primes(spark):
    pairs = spark.range(300).select("id", ((F.col("id") * 7) % (1 << 20)).alias("value"))
    f = B.build_sparse_linear(pairs, "id", "value", k=20, p_bits=61)
    assert M.member_mismatches(pairs, f, "id", "value") == 0 and f.get(5) == 35 and f.get(-1) is None
    absent = spark.range(10**6, 10**6 + 20_000)
    assert M.false_value_rate(f, absent, "id")["hits"] == 0
    with pytest.raises(ValueError):
        B.build_sparse_linear(pairs, "id", "value", k=20, p_bits=62)


def test_registered_queries_have_stable_columns(spark, small):
    assert set(Q.oracle_sql()) <= set(Q.queries())
    for name in ("indeg_order", "md5_edges", "space_table"):
        assert Q.queries()[name](spark, small).columns
    assert isinstance(BuildError("x"), ValueError)


def test_last_values_in_state(spark, small, tmp_path):
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        path = f"{small}/events.parquet"
        got = S.run_once(S.latest_value(S.events_stream(spark, path), "user_id", "value"), "last_values", f"{tmp_path}/c", "update")
        truth = spark.read.parquet(path).groupBy("user_id").agg(F.max_by("value", "ts").alias("value"))
        assert got.select("user_id", "value").exceptAll(truth).isEmpty() and got.count() == truth.count()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)


def test_bucketed_builders(orders):
    for builder in (B.build_acyclic, B.build_matched, B.build_sparse_linear, B.build_xor_sparse):
        f = B.bucketed(builder, orders, "l_orderkey", "value", k=5, bucket_c=8.0)
        assert f.spec.shards * max(1, f.spec.buckets) > 10 and M.member_mismatches(orders, f, "l_orderkey", "value") == 0


def test_tried_blocks_have_methods_that_are_compiled(spark, orders):
    f = B.build_bucketed_sparse(orders, "l_orderkey", "value", k=5)
    found = lookup(orders.select("l_orderkey"), f, "l_orderkey", "_v").agg(F.count("_v").alias("hits"))
    assert f.blocks() > 3 and found.collect()[0]["hits"] == f.n
    plan = found._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("codegen"))
    assert max(map(int, re.findall(r"maxMethodCodeSize:(\d+)", plan))) < 8_000  # bytes above which a JVM compiles no method


def test_broadcasts_follow_the_heap_of_the_driver(spark, orders, monkeypatch):
    f = B.build_acyclic(orders, "l_orderkey", "value", k=5)
    joins = lambda: lookup(orders.select("l_orderkey"), f, "l_orderkey")._jdf.queryExecution().optimizedPlan().toString()
    heap = spark._jvm.java.lang.Runtime.getRuntime().maxMemory()
    assert 0 < lookups.broadcast_limit(spark) <= min(lookups.BROADCAST_BYTES, heap // 16) and "strategy=broadcast" in joins()
    monkeypatch.setattr(lookups, "broadcast_limit", lambda spark: f.bytes() - 1)
    assert "strategy=shuffle_hash" in joins() and M.member_mismatches(orders, f, "l_orderkey", "value") == 0


def test_windows_samples_and_plans(spark, orders):
    rows = spark.createDataFrame([("a", 1), ("a", 2), ("a", 2), ("b", 5)], "k string, v int")
    assert sorted(r["rank"] for r in R.ranked(rows, "v", "k").where("k = 'a'").collect()) == [1, 1, 3]
    assert [r["change"] for r in R.moving_mean(rows.where("k = 'a'"), "v", "v", "k").orderBy("v").collect()] == [None, 1, 0]
    assert R.sample_by(rows, "k", {"b": 1.0}).count() == 1
    assert B.plan_shards(orders, "l_orderkey", per_shard=500) == 3 and 2 <= B.plan_shards(orders, "l_orderkey", approx=True, per_shard=500) <= 4


def test_components_by_recursion(spark):
    spark.createDataFrame([(1, 2), (2, 3), (7, 8)], "u long, v long").createOrReplaceTempView("few_edges")
    assert {r["slot"]: r["component"] for r in spark.sql(sqlapi.components_sql("few_edges")).collect()} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7}


def test_experiments_are_registered_whole(monkeypatch):
    from keyloom import queries, workloads

    seen = {}
    for name in ("creation", "c_sweep", "sparse_sweep", "bucketing", "hash_quality", "lookup_speed", "growth"):
        monkeypatch.setattr(workloads, name, lambda spark, *d, _name=name, **options: seen.update({_name: options}))
    for name in ("w3_creation", "w9_c_sweep", "w10_sparse_sweep", "w11_bucketing", "w15_hash_quality", "w18_lookup_speed", "growth"):
        queries.QUERIES[name](None, "")
    assert len(seen) == 7 and not any(seen.values())
