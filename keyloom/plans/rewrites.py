"""Rewrites of plans by filters. PySpark can't add optimizer rules, so these are functions that one calls."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyloom.operators.lookup import Filter, lookup
from keyloom.operators.relational import semi_reduce


def reduce(fact: DataFrame, filter: Filter, key) -> DataFrame:
    """Drops rows that can't join before the join shuffles them; a few that can't may stay."""
    return semi_reduce(fact, filter, key)


def join_to_lookup(fact: DataFrame, filter: Filter, key, payload: str, exact: DataFrame | None = None) -> DataFrame:
    """An inner join with a table of one small payload column, as a lookup: that table is not shuffled.

    Rows with absent keys get a false value with the filter's error; with ``exact`` (the table itself) hits are checked by a semi-join.
    """
    rows = lookup(fact, filter, key, payload).where(F.col(payload).isNotNull())
    keys = [key] if isinstance(key, str) else list(key)
    return rows if exact is None else rows.join(exact.select(*keys), keys, "left_semi")
