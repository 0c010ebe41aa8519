"""Relational operators around filters: members and absents, reductions of joins, bands, as-of values, in-degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyloom.functions.hashing import key_columns
from keyloom.operators.lookup import Filter, lookup


#: Values of a column that gets codes.
MAX_CODES = 100_000


def members(df: DataFrame, filter: Filter, key) -> DataFrame:
    """Rows whose key the filter knows (and, but for its error, no others)."""
    return lookup(df, filter, key, "_v").where("_v is not null").drop("_v")


def absents(df: DataFrame, filter: Filter, key) -> DataFrame:
    """Rows whose key it doesn't know."""
    return lookup(df, filter, key, "_v").where("_v is null").drop("_v")


def semi_reduce(fact: DataFrame, filter: Filter, key, verify: DataFrame | None = None) -> DataFrame:
    """``fact`` without rows that can't join. With ``verify`` (the set itself, same key names) the result is exact: what is left of the fact is checked."""
    left = members(fact, filter, key)
    return left if verify is None else left.join(verify.select(*key_columns(key)).distinct(), key_columns(key), "left_semi")


def checked(looked: DataFrame, members: DataFrame, key: str, members_key: str, out: str = "value") -> DataFrame:
    """Looked-up rows, made exact: a value that a key outside the set got becomes NULL."""
    known = members.select(F.col(members_key).alias("_member")).distinct()
    rows = looked.join(known, F.col(key) == F.col("_member"), "left")
    return rows.select(*[F.when(F.col("_member").isNotNull(), F.col(c)).alias(c) if c == out else F.col(c) for c in looked.columns])


def compare(df: DataFrame, filter: Filter, truth: DataFrame, key, value: str) -> DataFrame:
    """(keys, stored, true) where a lookup and the truth differ, NULLs being equal."""
    keys = key_columns(key)
    looked = lookup(df.select(*keys), filter, key, "stored")
    both = looked.join(truth.select(*keys, F.col(value).cast("long").alias("true")), keys, "left")
    return both.where(~F.col("stored").eqNullSafe(F.col("true")))


def indegree(edges: DataFrame, target: str, source: str | None = None, distinct: bool = False) -> DataFrame:
    """(target, value): how many rows, or how many distinct sources, point to each target."""
    rows = edges.select(source, target).distinct() if distinct else edges
    return rows.groupBy(target).agg(F.count("*").alias("value"))


def band_join(df: DataFrame, bands: DataFrame, value: str) -> DataFrame:
    """Each row with the band [low, high) that its value is in. ``bands`` is a small grid and is broadcast if Spark finds it small."""
    return df.join(bands, (F.col(value) >= F.col("low")) & (F.col(value) < F.col("high")))


def asof_value(events: DataFrame, versions: DataFrame, key: str, ts: str = "ts", value: str = "value") -> DataFrame:
    """Each event with the last version of its key at or before its time: one union and one window, no range join."""
    rows = events.select(key, ts, F.lit(None).cast(versions.schema[value].dataType).alias("_v"), F.struct(*events.columns).alias("_e"), F.lit(1).alias("_o"))
    marks = versions.select(key, ts, F.col(value).alias("_v"), F.lit(None).cast(rows.schema["_e"].dataType).alias("_e"), F.lit(0).alias("_o"))
    w = Window.partitionBy(key).orderBy(ts, "_o").rowsBetween(Window.unboundedPreceding, 0)
    return rows.unionByName(marks).withColumn("_v", F.last("_v", ignorenulls=True).over(w)).where("_o = 1").select("_e.*", F.col("_v").alias(f"{value}_asof"))


def top_k(df: DataFrame, by: str, k: int, *ties: str) -> DataFrame:
    """The k rows with the largest ``by``; ties by the other columns."""
    return df.orderBy(F.desc(by), *ties).limit(k)


def ranked(df: DataFrame, by: str, *partition: str, tiles: int = 4) -> DataFrame:
    """``df`` with row_number, rank, dense_rank, percent_rank and a tile of ``by``, falling, within each partition."""
    w = Window.partitionBy(*partition).orderBy(F.desc(by))
    return df.withColumns({"nth": F.row_number().over(w), "rank": F.rank().over(w), "dense": F.dense_rank().over(w), "percent": F.percent_rank().over(w), "tile": F.ntile(tiles).over(w)})


def moving_mean(df: DataFrame, value: str, order: str, *partition: str, back: int = 4) -> DataFrame:
    """A mean over each row and some before it, and the change from the row before."""
    w = Window.partitionBy(*partition).orderBy(order)
    return df.withColumns({"mean": F.avg(value).over(w.rowsBetween(-back, 0)), "change": F.col(value) - F.lag(value).over(w)})


def sample_by(df: DataFrame, column: str, shares: dict, seed: int = 42) -> DataFrame:
    """A seeded sample with a share for each value of a column."""
    return df.sampleBy(column, shares, seed)


def key_difference(a: DataFrame, b: DataFrame, all_rows: bool = False) -> tuple[DataFrame, DataFrame]:
    """What a has and b hasn't, and what both have."""
    return (a.exceptAll(b), a.intersectAll(b)) if all_rows else (a.subtract(b), a.intersect(b))


def dictionary(df: DataFrame, column: str, code: str = "code") -> DataFrame:
    """(column, code): each distinct value and its place in sorted order. Refused for a domain of more than MAX_CODES values: these are ranked in one task."""
    domain = df.select(column).where(F.col(column).isNotNull()).distinct()
    if domain.limit(MAX_CODES + 1).count() > MAX_CODES:
        raise ValueError(f"{column} has more than {MAX_CODES} values")
    return domain.withColumn(code, (F.dense_rank().over(Window.orderBy(column)) - 1).cast("long"))


def encode(df: DataFrame, column: str, codes: DataFrame, code: str = "code") -> DataFrame:
    return df.join(codes, column)


def check_function(df: DataFrame, key, value: str, k: int, on_conflict: str = "error") -> DataFrame:
    """(keys, value) with one row for each key. on_conflict: error, min or max of the values; NULL keys and values out of range raise an error."""
    keys = key_columns(key)
    null = F.lit(False)
    for c in keys:
        null = null | F.col(c).isNull()
    v = F.col(value).cast("long")
    bad = null | v.isNull() | (v < 0) | (v >= F.lit(1 << k))
    rows = df.select(*keys, F.when(bad, F.raise_error(F.lit(f"a key is NULL or a value doesn't fit in {k} bits"))).otherwise(v).alias("value"))
    if on_conflict == "error":
        pick = F.when(F.min("value") == F.max("value"), F.min("value")).otherwise(F.raise_error(F.lit("two values for one key")))
    elif on_conflict in ("min", "max"):
        pick = getattr(F, on_conflict)("value")
    else:
        raise ValueError(on_conflict)
    return rows.groupBy(*keys).agg(pick.cast("long").alias("value"))
