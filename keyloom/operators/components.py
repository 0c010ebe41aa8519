"""Connected components on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.plans.scratch import remove, written


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Connected components of an edge list of longs: (node, root), one row per node that has an edge to another node.

    Each round hooks every node to the neighbour (or itself) of least pseudo-random rank, renames the ends of all edges
    by that and drops loops and repeats; the rank changes from round to round, so that long chains shrink by a constant
    factor, too. ``root`` is some node of the component, the same for all its nodes. Null ends are dropped.
    Minima are combined before each shuffle, and the joins read plain tables, so that a hub's edges can be split.
    """
    spark = edges.sparkSession
    left, where = written(edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u <> v").distinct(), "edges")
    roots: DataFrame | None = None
    for round_no in range(max_rounds):
        if left.isEmpty():
            break
        ends = left.unionByName(left.select(F.col("v").alias("u"), F.col("u").alias("v")))
        rank = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(round_no)).alias("h"), F.col(c).alias("n"))
        hooked = ends.groupBy("u").agg(F.min(rank("v")).alias("m")).select(F.col("u").alias("x"), F.least("m", rank("u"))["n"].alias("p"))
        hooks, _ = written(hooked, "hooks")
        renamed = left.join(hooks, F.col("u") == F.col("x")).select(F.col("p").alias("pu"), "v")
        renamed = renamed.join(hooks, F.col("v") == F.col("x")).select(F.col("pu").alias("u"), F.col("p").alias("v")).where("u <> v")
        ordered = renamed.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
        before, (left, where) = where, written(ordered, "edges")
        remove(spark, before)
        if roots is None:
            roots = hooks.select(F.col("x").alias("node"), F.col("p").alias("root"))
        else:
            later = hooks.select("x", "p")
            joined = roots.join(later, F.col("root") == F.col("x"), "left").select("node", F.coalesce("p", "root").alias("root"))
            roots, _ = written(joined, "roots")
    else:
        raise RuntimeError(f"no end after {max_rounds} rounds")
    if roots is None:
        return left.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots
