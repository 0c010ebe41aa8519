"""Filters from SQL: a vectorised look-up function, table functions, hash functions, and components by recursion."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from keyloom.functions.hashing import np_derived, np_xxhash64
from keyloom.operators.lookup import Filter, np_evaluate
from keyloom.plans.params import acyclic_probability, modulus_for

#: A filter that a function closes over may have so many bytes.
FUNCTION_BYTES = 64 << 20


def register_lookup(spark: SparkSession, name: str, filter: Filter) -> None:
    """``name(key)``, for filters with one long key: rows of tables go to the workers by broadcast, so the size is checked."""
    if filter.key_types != ["bigint"] or filter.spec.family != "xx64":
        raise ValueError("only one BIGINT key")
    if filter.bytes() > FUNCTION_BYTES:
        raise ValueError(f"the filter has more than {FUNCTION_BYTES} bytes; use lookup()")
    rows = {r["shard"]: r.asDict() for r in filter.tables.collect()}
    shared, spec = spark.sparkContext.broadcast(rows), filter.spec

    def values(key: pd.Series) -> pd.Series:
        known = key.notna().to_numpy()
        k = key.fillna(0).to_numpy(np.int64)
        d0, d1 = np_xxhash64(1, k), np_xxhash64(2, k)
        shard = np_derived(spec.seed, 0, d0, d1) % spec.shards
        out = np.full(len(k), -1)
        for s in np.unique(shard):
            at = np.nonzero(shard == s)[0]
            if int(s) in shared.value:
                out[at] = np_evaluate(spec, shared.value[int(s)], d0[at], d1[at])
        return pd.Series(out, dtype="Int64").mask((out < 0) | ~known)

    def batches(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield values(part)

    batches.__annotations__ = {"parts": Iterator[pd.Series], "return": Iterator[pd.Series]}
    spark.udf.register(name, F.pandas_udf(batches, "long"))


def register_functions(spark: SparkSession) -> None:
    """``vf_slot(seed, role, key, n)`` in plain SQL, and the table functions ``vf_params(n, k, error)`` and ``vf_spec(json)``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vf_slot(seed BIGINT, role BIGINT, k BIGINT, n BIGINT) RETURNS BIGINT RETURN pmod(xxhash64(seed, role, xxhash64(1L, k), xxhash64(2L, k)), n)")
    spark.udtf.register("vf_params", F.udtf(_Params, returnType="c double, slots long, modulus_bits int, bits_per_key double, expected_draws double"))


class _Params:
    def eval(self, n: int, k: int, error: float):
        for c in (2.09, 2.25, 2.5, 3.0, 4.0):
            bits = (modulus_for(k, None, error) - 1).bit_length()
            yield c, int(np.ceil(c * n)), bits, c * bits, 1 / acyclic_probability(c)


def register_slots(spark: SparkSession, name: str, filter: Filter) -> None:
    """The filter's slots as a view (shard, slot, g)."""
    filter.tables.select("shard", F.posexplode("g").alias("slot", "g")).createOrReplaceTempView(name)


def components_sql(edges: str) -> str:
    """SQL that both Spark and DuckDB run: the least slot of each slot's tree, for a small edge view (u, v) that is a forest.

    Walks never turn back, so in a forest they end; Spark's recursion has no UNION that would stop them elsewhere.
    """
    return f"""
WITH RECURSIVE sym(a, b) AS (SELECT u, v FROM {edges} UNION ALL SELECT v, u FROM {edges}),
walk(a, place, before) AS (
  SELECT DISTINCT a, a, CAST(-1 AS BIGINT) FROM sym
  UNION ALL SELECT w.a, s.b, w.place FROM walk w JOIN sym s ON w.place = s.a WHERE s.b <> w.before)
SELECT a AS slot, min(place) AS component FROM walk GROUP BY a"""
