"""The acyclic construction as one graph over the whole set, on DataFrames alone: nothing of it is collected.

Edges are columns, components come from contraction rounds, the forest test is one aggregate, and trees are solved either whole or
round by round along a frontier. Every round shuffles the edges, so shards (``build_acyclic``) are the way for large sets; this one is
the reference that they are compared with.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyloom.functions.hashing import FIRST, MASK, SECOND, check_key_types, derived, digests, next_seed
from keyloom.operators import kernels as K
from keyloom.operators.components import components
from keyloom.plans.params import check_c, modulus_for
from keyloom.plans.scratch import written


@dataclass(frozen=True)
class GlobalFilter:
    """Slots as rows (slot, g), and what a lookup needs: the seed and the number of slots."""

    slots: DataFrame
    key_types: list[str]
    n_slots: int
    seed: int
    k: int
    modulus: int
    family: str
    attempts: int


def md5_number(seed: int, role: int, key: str) -> Column:
    """A 60-bit number from the MD5 of ``seed:role:key``; any SQL engine can repeat it."""
    text = F.concat(F.lit(f"{seed}:{role}:"), F.col(key).cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def graph(df: DataFrame, key, kinds: list[str], n_slots: int, modulus: int, seed: int, family: str, keep: list[str]) -> DataFrame:
    """(keep..., u, v, mask): both slots and the mask of each key; the second slot is never the first."""
    if family == "md5":
        first, second, third = (md5_number(seed, r, key) for r in (FIRST, SECOND, MASK))
        rows = df
    else:
        d0, d1 = digests(key, kinds, family)
        rows = df.withColumns({"d0": d0, "d1": d1})
        first, second, third = (derived(F.lit(seed).cast("long"), r, family) for r in (FIRST, SECOND, MASK))
    u = F.pmod(first, F.lit(n_slots).cast("long"))
    v = F.pmod(u + 1 + F.pmod(second, F.lit(n_slots - 1).cast("long")), F.lit(n_slots).cast("long"))
    return rows.select(*keep, u.alias("u"), v.alias("v"), F.pmod(third, F.lit(modulus).cast("long")).alias("mask"))


def neighbours(edges: DataFrame) -> DataFrame:
    """(a, b, rhs): every edge from both of its ends."""
    return edges.select(F.col("u").alias("a"), F.col("v").alias("b"), "rhs").unionByName(edges.select(F.col("v").alias("a"), F.col("u").alias("b"), "rhs"))


def forest_components(edges: DataFrame) -> DataFrame | None:
    """(slot, component) if the edges are a forest, else None. The component is its least slot."""
    counts = edges.agg(F.count("*").alias("n"), F.countDistinct(F.least("u", "v"), F.greatest("u", "v")).alias("d")).first()
    if counts["n"] != counts["d"]:
        return None
    roots = components(edges, "u", "v")
    least = roots.groupBy("root").agg(F.min("node").alias("component")).withColumnRenamed("root", "of")
    labels, _ = written(roots.join(least, F.col("root") == F.col("of")).select(F.col("node").alias("slot"), "component"), "labels")
    sizes = labels.agg(F.count("*").alias("slots"), F.countDistinct("component").alias("trees")).first()
    return labels if counts["n"] == sizes["slots"] - sizes["trees"] else None


def build_acyclic_global(df: DataFrame, key, value: str, *, k: int = 1, modulus: int | None = None, error: float = 2.0**-32, c: float = 2.5, solve: str = "component", seed: int = 42, family: str = "xx64", max_attempts: int = 32) -> GlobalFilter:
    """One graph for the whole set. solve: ``component`` gives whole trees to tasks, ``frontier`` goes from the roots outwards by joins."""
    check_c(c)
    if solve not in ("component", "frontier"):
        raise ValueError(solve)
    modulus, kinds = modulus_for(k, modulus, error), check_key_types(df, key)
    n = df.count()
    n_slots = max(2, math.ceil(c * n))
    for attempt in range(1, max_attempts + 1):
        own = next_seed(seed, 0, attempt) if family != "md5" else seed + attempt - 1
        rows = graph(df, key, kinds, n_slots, modulus, own, family, [F.col(value).cast("long").alias("value")])
        edges, _ = written(rows.select("u", "v", F.pmod(F.col("value") - F.col("mask"), F.lit(modulus).cast("long")).alias("rhs")), "edges")
        labels = forest_components(edges)
        if labels is not None:
            slots = _by_component(edges, labels, modulus, n) if solve == "component" else _by_frontier(edges, labels, modulus)
            return GlobalFilter(written(slots, "slots")[0], kinds, n_slots, own, k, modulus, family, attempt)
    raise K.BuildError(f"{max_attempts} graphs were not enough")


#: Edges of a task that solves trees.
EDGES_A_TASK = 1 << 16


def _by_component(edges: DataFrame, labels: DataFrame, modulus: int, n: int) -> DataFrame:
    """Whole trees, dealt to tasks by their component; a task solves all of its trees at once."""

    def run(forest: pa.Table) -> pa.Table:
        ends = np.stack([forest.column(c).to_numpy() for c in ("u", "v")])
        slots, at = np.unique(ends.ravel(), return_inverse=True)
        u, v = at.reshape(2, -1)
        g = K.solve_forest(K.peel(np.stack((u, v)), len(slots)), u, v, forest.column("rhs").to_numpy(), len(slots), modulus).g
        return pa.table({"slot": slots, "g": g})

    part = F.pmod(F.xxhash64("component"), F.lit(max(1, -(-n // EDGES_A_TASK)))).alias("part")
    trees = edges.join(labels, F.col("u") == F.col("slot")).select(part, "u", "v", "rhs")
    return trees.groupBy("part").applyInArrow(run, "slot long, g long")


def _by_frontier(edges: DataFrame, labels: DataFrame, modulus: int) -> DataFrame:
    both, _ = written(neighbours(edges), "neighbours")
    done, _ = written(labels.where("slot = component").select("slot", F.lit(0).cast("long").alias("g")), "frontier")
    front = done
    for _ in range(10_000):
        found = both.join(front, F.col("a") == F.col("slot")).select(F.col("b").alias("slot"), F.pmod(F.col("rhs") - F.col("g"), F.lit(modulus).cast("long")).alias("g"))
        front, _ = written(found.join(done.select(F.col("slot").alias("s")), F.col("slot") == F.col("s"), "left_anti"), "frontier")
        if front.isEmpty():
            return done
        done = done.unionByName(front)
    raise RuntimeError("the trees don't end")


def lookup_global(df: DataFrame, filter: GlobalFilter, key, out: str = "value") -> DataFrame:
    """Two equi-joins with the slot rows; slots that no key touches hold 0."""
    rows = graph(df, key, filter.key_types, filter.n_slots, filter.modulus, filter.seed, filter.family, [F.col(c) for c in df.columns])
    at = lambda name: filter.slots.select(F.col("slot").alias(f"_{name}s"), F.col("g").alias(f"_{name}g"))
    rows = rows.join(at("a"), F.col("u") == F.col("_as"), "left").join(at("b"), F.col("v") == F.col("_bs"), "left")
    x = F.pmod(F.coalesce("_ag", F.lit(0)) + F.coalesce("_bg", F.lit(0)) + F.col("mask"), F.lit(filter.modulus).cast("long"))
    return rows.select(*df.columns, F.when(x < (1 << filter.k), x).alias(out))
