"""Fixed-width bit packing of slot tables, and tables as rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def width_of(modulus: int) -> int:
    """Bits of a residue."""
    return max(1, (modulus - 1).bit_length())


def pack(values: np.ndarray, width: int) -> bytes:
    """Values below 2^width, the least significant bit first, one after the other."""
    if not 1 <= width <= 63:
        raise ValueError(f"width {width}")
    values = np.asarray(values, np.int64)
    if len(values) and (values.min() < 0 or int(values.max()) >> width):
        raise ValueError(f"a value doesn't fit in {width} bits")
    bits = (values[:, None] >> np.arange(width)) & 1
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack(data: bytes, width: int, n: int) -> np.ndarray:
    bits = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")[: n * width].reshape(n, width)
    return (bits.astype(np.int64) << np.arange(width)).sum(axis=1)


def gather(data: bytes, width: int, at: np.ndarray) -> np.ndarray:
    """Only the values at some places."""
    raw = np.frombuffer(data, np.uint8)
    bit = at[:, None] * width + np.arange(width)
    return (((raw[bit >> 3] >> (bit & 7).astype(np.uint8)) & 1).astype(np.int64) << np.arange(width)).sum(axis=1)


def to_rows(tables: DataFrame) -> DataFrame:
    """(shard, slot, g): one row for each slot."""
    return tables.select("shard", F.posexplode("g").alias("slot", "g"))


def to_arrays(slots: DataFrame) -> DataFrame:
    """Rows back to (shard, g array)."""
    whole = slots.groupBy("shard").agg(F.array_sort(F.collect_list(F.struct("slot", "g"))).alias("cells"))
    return whole.select("shard", F.transform("cells", lambda c: c["g"]).alias("g"))


def ordered_slots(tables: DataFrame, n: int = 8) -> DataFrame:
    """Slots range-partitioned and sorted, for packing in order."""
    return to_rows(tables).repartitionByRange(n, "shard", "slot").sortWithinPartitions("shard", "slot")


def offsets(tables: DataFrame) -> DataFrame:
    """(shard, n_slots, first): where each shard's slots begin if all are laid out in order."""
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)  # one row for each shard
    return tables.select("shard", "n_slots", F.coalesce(F.sum("n_slots").over(before), F.lit(0)).alias("first"))
