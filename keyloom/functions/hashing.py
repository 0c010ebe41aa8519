"""Digests of keys, and the hashes that filters derive from them, in Catalyst and in NumPy with the same results.

A key becomes two 64-bit digests at the scan. Everything later hashes these 16 bytes, so key text is never shuffled. A derived hash is
the public 64-bit mixing of ``xxhash64`` over (seed, role, d0, d1); seeds are longs and may be columns.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: The constants of XXH64.
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
#: The prime of the 2-universal family; products of two residues stay below 2^62.
UNIVERSAL_PRIME = (1 << 31) - 1
FAMILIES = ("xx64", "md5", "two_universal")
#: Roles of derived hashes.
SHARD, FIRST, SECOND, MASK, CHOICE = range(5)


def key_columns(key: str | list[str]) -> list[str]:
    return [key] if isinstance(key, str) else list(key)


def check_key_types(df: DataFrame, key: str | list[str]) -> list[str]:
    """The types of the key columns; floating-point and map keys are refused."""
    kinds = []
    for name in key_columns(key):
        kind = df.schema[name].dataType
        if isinstance(kind, (T.FloatType, T.DoubleType, T.MapType, T.VariantType)):
            raise TypeError(f"{name}: {kind.simpleString()} can't be a key")
        kinds.append(kind.simpleString())
    return kinds


def digests(key: str | list[str], kinds: list[str], family: str = "xx64") -> tuple[Column, Column]:
    """The two digests of a key. Keys are cast to ``kinds`` first: ``xxhash64`` tells an INT from a BIGINT."""
    cols = [F.col(c).cast(k) for c, k in zip(key_columns(key), kinds)]
    if family == "md5":
        text = F.concat_ws("\x1f", *[c.cast("string") for c in cols])
        half = lambda at: F.conv(F.substring(F.md5(text.cast("binary")), at, 15), 16, 10).cast("long")
        return half(1), half(17)
    if family == "two_universal":
        whole = cols[0].cast("long") if kinds[0] in ("int", "bigint", "smallint", "tinyint") and len(cols) == 1 else F.xxhash64(*cols)
        return F.pmod(whole, F.lit(UNIVERSAL_PRIME)), F.lit(0).cast("long")
    return F.xxhash64(F.lit(1).cast("long"), *cols), F.xxhash64(F.lit(2).cast("long"), *cols)


def with_digest(df: DataFrame, key: str | list[str], kinds: list[str] | None = None, family: str = "xx64") -> DataFrame:
    d0, d1 = digests(key, kinds or check_key_types(df, key), family)
    return df.withColumns({"d0": d0, "d1": d1})


def derived(seed: Column, role: int | Column, family: str = "xx64", d0: str = "d0", d1: str = "d1") -> Column:
    """A hash of the digests (signed long); for the 2-universal family a residue of its prime."""
    if family == "two_universal":
        a = F.pmod(F.xxhash64(seed, F.lit(2 * role).cast("long")), F.lit(UNIVERSAL_PRIME - 1)) + 1
        b = F.pmod(F.xxhash64(seed, F.lit(2 * role + 1).cast("long")), F.lit(UNIVERSAL_PRIME))
        return F.pmod(a * F.col(d0) + b, F.lit(UNIVERSAL_PRIME))
    return F.xxhash64(seed, role if isinstance(role, Column) else F.lit(role).cast("long"), F.col(d0), F.col(d1))


def shard_of(n_shards: int | Column, seed: int = 42, family: str = "xx64") -> Column:
    n = n_shards if isinstance(n_shards, Column) else F.lit(n_shards)
    return F.pmod(derived(F.lit(seed).cast("long"), SHARD, family), n.cast("long")).cast("int")


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _mix(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    h = seed + _P5 + np.uint64(8)
    h = h ^ (_rotl(value * _P2, 31) * _P1)
    h = _rotl(h, 27) * _P1 + _P4
    h = (h ^ (h >> np.uint64(33))) * _P2
    h = (h ^ (h >> np.uint64(29))) * _P3
    return h ^ (h >> np.uint64(32))


def np_xxhash64(*columns) -> np.ndarray:
    """What ``xxhash64`` gives for columns of longs."""
    with np.errstate(over="ignore"):
        h = np.full(1, 42, np.uint64)
        for c in columns:
            h = _mix(np.atleast_1d(np.asarray(c, np.int64)).view(np.uint64), h)
    return h.view(np.int64)


def np_derived(seed, role: int, d0: np.ndarray, d1: np.ndarray, family: str = "xx64") -> np.ndarray:
    """``seed``: a number, or for the xx64 family an array."""
    if family == "two_universal":
        a = int(np_xxhash64(seed, 2 * role)[0]) % (UNIVERSAL_PRIME - 1) + 1
        b = int(np_xxhash64(seed, 2 * role + 1)[0]) % UNIVERSAL_PRIME
        return (a * d0 + b) % UNIVERSAL_PRIME
    return np.broadcast_to(np_xxhash64(seed, role, d0, d1), d0.shape)


def next_seed(*parts: int) -> int:
    """The seed of an attempt, from whatever tells it from others."""
    return int(np_xxhash64(*parts)[0])
