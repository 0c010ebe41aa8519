"""Primes, generators and the choice of the two primes of the sparse-linear construction."""

from __future__ import annotations

import math
import random
from dataclasses import dataclass
from functools import lru_cache

#: Bases that make the Miller-Rabin test exact below 2^64.
_WITNESSES = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37)


def is_prime(n: int) -> bool:
    if n < 2:
        return False
    for w in _WITNESSES:
        if n % w == 0:
            return n == w
    odd, twos = n - 1, 0
    while odd % 2 == 0:
        odd, twos = odd // 2, twos + 1
    return all(_passes(n, w, odd, twos) for w in _WITNESSES)


def _passes(n: int, w: int, odd: int, twos: int) -> bool:
    x = pow(w, odd, n)
    if x in (1, n - 1):
        return True
    return any((x := x * x % n) == n - 1 for _ in range(twos - 1))


def next_prime(n: int) -> int:
    """The first prime that is n or more."""
    n = max(2, n)
    while not is_prime(n):
        n += 1
    return n


@lru_cache(maxsize=4096)
def prime_factors(n: int) -> tuple[int, ...]:
    """The distinct prime factors, by trial division: for numbers of the size of a table."""
    found, d = [], 2
    while d * d <= n:
        if n % d == 0:
            found.append(d)
            while n % d == 0:
                n //= d
        d += 1
    return tuple(found + [n] * (n > 1))


def is_primitive_root(a: int, q: int) -> bool:
    """Whether the powers of a are all residues of the prime q but 0."""
    return a % q != 0 and (q == 2 or all(pow(a, (q - 1) // f, q) != 1 for f in prime_factors(q - 1)))


@dataclass(frozen=True)
class Primes:
    """q slots over the field of p elements; how often generators and primes were drawn."""

    q: int
    p: int
    generator_draws: int
    prime_draws: int


@lru_cache(maxsize=4096)
def choose_primes(n: int, eps: float, p_bits: int, seed: int = 42, method: str = "direct", field: str = "primitive") -> Primes:
    """q: the first prime that is n(1+eps) or more. p: a random prime of p_bits bits, a generator modulo q unless ``field`` is any_prime.

    method ``list`` draws one generator and accepts p if its residue is among all generators made from that one; ``direct`` tests p's residue itself.
    """
    if n < 1 or eps <= 0 or p_bits < 2:
        raise ValueError("n >= 1, eps > 0 and p_bits >= 2 are needed")
    r = random.Random(f"{seed}:{n}:{p_bits}")
    q = next_prime(max(3, math.ceil(n * (1 + eps))))
    generator_draws = prime_draws = 0
    good: set[int] | None = None
    if field == "primitive" and method == "list":
        while True:
            generator_draws += 1
            a = r.randrange(1, q)
            if is_primitive_root(a, q):
                break
        good, power = set(), 1
        for e in range(1, q):
            power = power * a % q
            if math.gcd(e, q - 1) == 1:
                good.add(power)
    while True:
        prime_draws += 1
        p = r.randrange(1 << (p_bits - 1), 1 << p_bits) | 1
        if p_bits == 2 and prime_draws % 2:
            p = 2
        if p == q or not is_prime(p):
            continue
        if field == "any_prime" or (p % q in good if good is not None else is_primitive_root(p, q)):
            return Primes(q, p, generator_draws, prime_draws)
        if prime_draws > 200_000:
            raise ValueError(f"no prime of {p_bits} bits generates modulo {q}")
