"""Parameters of filters, checked once on the driver."""

from __future__ import annotations

import math
from dataclasses import dataclass

KEYS_PER_SHARD = 1 << 16
#: Residues are below this, so that a sum of three stays in a signed long.
MODULUS_LIMIT = 1 << 61


@dataclass(frozen=True)
class Spec:
    """What a kernel has to know. Not every kind of filter uses every field."""

    kind: str
    k: int = 1
    modulus: int = 0
    c: float = 2.5
    distinct: bool = True
    #: Trees hold 0 at their least slot.
    canonical: bool = False
    family: str = "xx64"
    seed: int = 42
    shards: int = 1
    max_attempts: int = 64
    component_cap: int = 0
    r: int = 2
    matching: str = "sorted"
    q_bits: int = 32
    eps: float = 0.1
    s: int = 3
    p_bits: int = 31
    max_blocks: int = 64
    #: Buckets of each shard; 0: a shard is one system.
    buckets: int = 0
    field: str = "primitive"
    load: float = 0.5
    tries: int = 1
    bits_per_key: float = 0.0
    hashes: int = 0

    @property
    def error(self) -> float:
        """The bound on the share of absent keys that get a value."""
        if self.kind in ("acyclic", "mutable", "xor", "peeled"):
            return 2.0**self.k / self.modulus
        if self.kind == "matched":
            return self.r / 2.0**self.q_bits
        if self.kind == "sparse":
            return self.max_blocks * 2.0**self.k / 2 ** (self.p_bits - 1)
        if self.kind in ("membership", "dict_membership"):
            return 0.5**self.hashes
        return 2.0**-64 if self.kind == "dict" else 1.0


#: Longs of each bucket in a shard's directory: where its slots begin, how many there are, its prime, its blocks, its seed.
DIRECTORY = ("first", "slots", "p", "blocks", "seed")


def check_k(k: int) -> None:
    if not 1 <= k <= 60:
        raise ValueError(f"k = {k}: values have 1 to 60 bits")


def modulus_for(k: int, modulus: int | None, error: float) -> int:
    """The given modulus, or the power of two that keeps the error."""
    check_k(k)
    if modulus is None:
        if not 0 < error < 1:
            raise ValueError("error must be between 0 and 1")
        modulus = 1 << (k + math.ceil(-math.log2(error)))
    if modulus < 1 << k:
        raise ValueError(f"modulus {modulus} is below 2^{k}")
    if modulus > MODULUS_LIMIT:
        raise ValueError(f"modulus {modulus} is above 2^61")
    return modulus


def check_c(c: float) -> None:
    if c <= 2:
        raise ValueError(f"c = {c}: a random graph with two endpoints for each key is acyclic with fair chance only for c > 2")


def shards_for(n: int, shards: int | str, per_shard: int = KEYS_PER_SHARD) -> int:
    return max(1, math.ceil(n / per_shard)) if shards == "auto" else int(shards)


def acyclic_probability(c: float, distinct: bool = True) -> float:
    """The chance that a random graph of n edges on cn vertices has no cycle, for large n."""
    return (math.exp(1 / c) if distinct else 1.0) * math.sqrt(1 - 2 / c)


def component_bound(n: int, c: float) -> int:
    """About the size of the largest tree of such a graph."""
    rate = 2 / c
    return max(8, math.ceil(3 * math.log(max(n, 2)) / (rate - 1 - math.log(rate))))


def bucket_tail(n: int, buckets: int, delta: float) -> float:
    """A bound for the chance that some bucket has more than (1 + delta) times the mean."""
    if delta <= 2 * math.e - 1:
        raise ValueError("delta must be above 2e - 1")
    return buckets * 2 ** (-delta * n / buckets)
