"""Changing values of a mutable acyclic filter: only the trees of the changed keys are solved again, and only their shards are written.

``recompute`` solves an affected tree anew from its edges; ``shift`` moves only the smaller side of each changed edge. Both
give filters that look up the same; recompute also gives the same bytes as a fresh build with the seeds kept. Keys that
the filter doesn't have can't be added; they are reported.

A batch has one new value for each key: without an order, or for the last of them in it, two different values for one key are an error, and so is a NULL.
Equal repetitions are one change; a NULL key changes nothing. Shards that no change touches stay in the files they are in, for tables and edges alike; after
COMPACT batches, or when a batch touches more than half of the shards, all are written together again.
"""

from __future__ import annotations

from itertools import groupby

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyloom.functions.hashing import CHOICE, FIRST, MASK, SECOND, derived, digests, shard_of
from keyloom.operators import kernels as K
from keyloom.operators.build import TABLES_SQL
from keyloom.operators.lookup import Filter
from keyloom.plans.scratch import written

#: Batches after which a filter's untouched shards are written together with the others.
COMPACT = 8


def edges(filter: Filter, pairs: DataFrame, key, value: str) -> DataFrame:
    """(shard, d0, d1, u, v, component, rhs, value): the graph, from the keys and the seeds; kept beside the filter for its updates."""
    spec = filter.spec
    d0, d1 = digests(key, filter.key_types, spec.family)
    rows = pairs.select(d0.alias("d0"), d1.alias("d1"), F.col(value).cast("long").alias("value")).withColumn("shard", shard_of(spec.shards, spec.seed, spec.family))
    heads = filter.tables.select(F.col("shard").alias("s"), "n_slots", "seed", "h")
    n, seed = F.col("n_slots"), F.col("seed")
    u = F.pmod(derived(seed, FIRST, spec.family), n)
    second = derived(seed, SECOND, spec.family)
    v = F.pmod(u + 1 + F.pmod(second, n - 1), n) if spec.distinct else F.pmod(second, n)
    m = F.lit(spec.modulus).cast("long")
    rows = rows.join(heads, F.col("shard") == F.col("s")).withColumns({"u": u, "v": v, "mask": F.pmod(derived(seed, MASK, spec.family), m)})
    rows = rows.select("shard", "d0", "d1", "u", "v", F.get("h", F.col("u").cast("int")).alias("component"), F.pmod(F.col("value") - F.col("mask"), m).alias("rhs"), "value")
    return rows.sortWithinPartitions("shard")  # so that files can be skipped by it


def latest(changes: DataFrame, key, order: str) -> DataFrame:
    """The last change of each key; ties in the order go by the other columns' JSON."""
    keys = [key] if isinstance(key, str) else list(key)
    rest = F.to_json(F.struct(*[F.col(f"`{c}`") for c in changes.columns]))
    nth = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc_nulls_last(order), rest))
    return changes.withColumn("_nth", nth).where("_nth = 1").drop("_nth")


def _wanted(filter: Filter, changes: DataFrame, key, value: str, order: str | None) -> DataFrame:
    """(cs, c0, c1, _new): one new value for each changed key; raises where a key has two, a NULL, or one that is too large."""
    rows = _located(filter, changes, key, value)
    known = F.lit(True)
    for c in [key] if isinstance(key, str) else key:
        known = known & F.col(c).isNotNull()
    last = F.col(order) if order else F.lit(0)
    at = rows.where(known).groupBy("cs", "c0", "c1", last.alias("_at")).agg(F.min("_new").alias("low"), F.max("_new").alias("high"), F.max(F.col("_new").isNull()).alias("null"))
    top = F.max(F.struct(F.col("_at").isNotNull().alias("has"), "_at", "low", "high", "null"))
    one = at.groupBy("cs", "c0", "c1").agg(top.alias("x")).select("cs", "c0", "c1", "x.low", "x.high", "x.null")
    bits = filter.spec.k
    checked = F.when(F.col("null"), F.raise_error(F.lit("a new value is NULL"))).when(F.col("low") != F.col("high"), F.raise_error(F.lit("two new values for one key")))
    checked = checked.when((F.col("low") < 0) | (F.col("low") >= F.lit(1 << bits)), F.raise_error(F.lit(f"a value doesn't fit in {bits} bits"))).otherwise(F.col("low"))
    return one.select("cs", "c0", "c1", checked.cast("long").alias("_new"))


def _located(filter: Filter, changes: DataFrame, key, value: str) -> DataFrame:
    d0, d1 = digests(key, filter.key_types, filter.spec.family)
    rows = changes.select("*", d0.alias("c0"), d1.alias("c1"), F.col(value).cast("long").alias("_new"))
    return rows.withColumn("cs", F.pmod(derived(F.lit(filter.spec.seed).cast("long"), 0, filter.spec.family, "c0", "c1"), F.lit(filter.spec.shards).cast("long")).cast("int"))


def rejected(filter: Filter, graph: DataFrame, changes: DataFrame, key, value: str = "value") -> DataFrame:
    """The changes whose keys the filter doesn't have."""
    rows = _located(filter, changes, key, value)
    on = (F.col("cs") == F.col("shard")) & (F.col("c0") == F.col("d0")) & (F.col("c1") == F.col("d1"))
    return rows.join(graph.select("shard", "d0", "d1"), on, "left_anti").select(*changes.columns)


def _split(df: DataFrame, shards: list[int]) -> tuple[DataFrame, DataFrame]:
    """Rows of those shards, and the others; files and row groups without them are skipped."""
    held = F.col("shard").isin(shards)
    return df.where(held), df.where(~held)


def update_values(filter: Filter, graph: DataFrame, changes: DataFrame, key, value: str = "value", *, mode: str = "recompute", order: str | None = None) -> tuple[Filter, DataFrame, DataFrame]:
    """(the changed filter, its edges, the slots that were written: (shard, slot, g))."""
    if filter.spec.kind != "mutable" or mode not in ("recompute", "shift"):
        raise ValueError(f"{filter.spec.kind}, {mode}")
    spec, modulus = filter.spec, filter.spec.modulus
    wanted, _ = written(_wanted(filter, changes, key, value, order), "wanted")
    shards = sorted(r["cs"] for r in wanted.select("cs").distinct().collect())  # a number for each touched shard
    if not shards:
        return filter, graph, filter.tables.select("shard", F.lit(0).cast("long").alias("slot"), F.lit(0).cast("long").alias("g")).limit(0)
    whole = 2 * len(shards) > spec.shards or (filter.version + 1) % COMPACT == 0
    own, others = _split(graph, shards)
    on = (F.col("cs") == F.col("shard")) & (F.col("c0") == F.col("d0")) & (F.col("c1") == F.col("d1"))
    new_value = F.coalesce("_new", "value")
    changed = own.join(wanted, on, "left").select("shard", "d0", "d1", "u", "v", "component", F.pmod(F.col("rhs") - F.col("value") + new_value, F.lit(modulus).cast("long")).alias("rhs"), new_value.alias("value"), F.col("rhs").alias("old_rhs"), (F.col("_new").isNotNull() & (F.col("_new") != F.col("value"))).alias("touched"))
    changed, _ = written(changed.sortWithinPartitions("shard"), "edges")
    hit = changed.where("touched").select(F.col("shard").alias("hs"), F.col("component").alias("hc")).distinct()
    affected = changed.join(hit, (F.col("shard") == F.col("hs")) & (F.col("component") == F.col("hc")), "left_semi")
    own_tables, other_tables = _split(filter.tables, shards)
    cells = own_tables.select(F.col("shard").alias("t"), "g")
    ends = affected.join(cells, F.col("shard") == F.col("t")).select("shard", "component", "u", "v", "rhs", "old_rhs", F.get("g", F.col("u").cast("int")).alias("gu"), F.get("g", F.col("v").cast("int")).alias("gv"))

    def solve(trees: pd.DataFrame) -> pd.DataFrame:
        """All affected trees of one shard."""
        shard = int(trees["shard"].iloc[0])
        u, v, rhs = (trees[c].to_numpy() for c in ("u", "v", "rhs"))
        if mode == "recompute":
            slots, at = np.unique(np.concatenate((u, v)), return_inverse=True)
            a, b = at[: len(u)], at[len(u) :]
            peeled = K.peel(np.stack((a, b)), len(slots))
            if not peeled.done:
                raise K.BuildError(f"shard {shard}: the edges given are no forest")
            g = K.solve_forest(peeled, a, b, rhs, len(slots), modulus).g
            out = dict(zip(slots.tolist(), g.tolist()))
        else:
            out = {}
            columns = ("component", "u", "v", "rhs", "old_rhs", "gu", "gv")
            rows = sorted(zip(*(trees[c].tolist() for c in columns)))
            for _, tree in groupby(rows, key=lambda row: row[0]):
                _, us, vs, new, old, gu, gv = map(list, zip(*tree))
                g = dict(zip(us, gu)) | dict(zip(vs, gv))
                for i in range(len(us)):
                    if new[i] != old[i]:
                        moved = K.shift_side(us, vs, g, i, new[i], modulus)
                        g |= moved
                        out |= moved
        now = {**dict(zip(u.tolist(), trees["gu"].tolist())), **dict(zip(v.tolist(), trees["gv"].tolist())), **out}
        held = np.array([now[x] + now[y] for x, y in zip(u.tolist(), v.tolist())], np.int64) % modulus
        if not (held == rhs).all():
            raise AssertionError(f"shard {shard}: a key of an affected tree isn't looked up as it was stored")
        return pd.DataFrame({"shard": shard, "slot": list(out), "g": list(out.values())}, columns=["shard", "slot", "g"]).astype({"shard": "int32", "slot": "int64", "g": "int64"})

    deltas, _ = written(ends.groupBy("shard").applyInPandas(solve, "shard int, slot long, g long"), "deltas")
    tables, edges_now = overlay(own_tables, deltas), changed.drop("old_rhs", "touched")
    if whole:
        tables, edges_now = written(other_tables.unionByName(tables), "filter")[0], written(others.unionByName(edges_now).sortWithinPartitions("shard"), "edges")[0]
    else:
        tables, edges_now = other_tables.unionByName(written(tables, "filter")[0]), others.unionByName(edges_now)
    return filter.with_tables(tables), edges_now, deltas


def overlay(tables: DataFrame, deltas: DataFrame) -> DataFrame:
    """Tables with some slots written over; by shard."""

    def put(table: pa.Table, cells: pa.Table) -> pa.Table:
        if not table.num_rows or not cells.num_rows:
            return table
        g = np.array(table.column("g")[0].as_py(), np.int64)
        g[cells.column("slot").to_numpy()] = cells.column("g").to_numpy()
        at = table.schema.get_field_index("g")
        return table.set_column(at, table.schema.field(at), pa.array([g], table.schema.field(at).type))

    return tables.groupBy("shard").cogroup(deltas.groupBy("shard")).applyInArrow(put, TABLES_SQL)


def update_matched(filter: Filter, changes: DataFrame, key, value: str = "value") -> tuple[Filter, DataFrame]:
    """(the changed two-table filter, the cells written: (shard, slot, value)): one cell of the second table for each key."""
    if filter.spec.kind != "matched":
        raise ValueError(filter.spec.kind)
    spec = filter.spec
    rows = _wanted(filter, changes, key, value, None).select(F.col("c0").alias("d0"), F.col("c1").alias("d1"), "_new", F.col("cs").alias("_shard"))
    side = filter.tables.select(*[F.col(c).alias(f"_t_{c}") for c in ("shard", "n_slots", "seed", "n_blocks", "extra", "p", "g", "h", "b")])
    n, seed = F.col("_t_n_slots"), F.col("_t_seed")
    ends = [F.floor(n * j / spec.r) if j else F.lit(0).cast("long") for j in range(spec.r + 1)]
    at = [ends[j] + F.pmod(derived(seed, CHOICE + j), ends[j + 1] - ends[j]) for j in range(spec.r)]
    which = F.pmod(derived(seed, MASK), F.lit(1 << spec.q_bits))
    for a in at:
        which = which.bitwiseXOR(F.get("_t_g", a.cast("int")))
    own = F.lit(None).cast("long")
    for j, a in enumerate(at):
        own = F.when(which == j, a).otherwise(own)
    cells, _ = written(rows.join(side, F.col("_shard") == F.col("_t_shard")).select(F.col("_shard").alias("shard"), own.alias("slot"), F.col("_new").alias("g")).where("slot is not null"), "cells")

    def put(table: pa.Table, new: pa.Table) -> pa.Table:
        if not table.num_rows or not new.num_rows:
            return table
        h = np.array(table.column("h")[0].as_py(), np.int64)
        h[new.column("slot").to_numpy()] = new.column("g").to_numpy()
        i = table.schema.get_field_index("h")
        return table.set_column(i, table.schema.field(i), pa.array([h], table.schema.field(i).type))

    tables = filter.tables.groupBy("shard").cogroup(cells.groupBy("shard")).applyInArrow(put, TABLES_SQL)
    return filter.with_tables(written(tables, "filter")[0]), cells
