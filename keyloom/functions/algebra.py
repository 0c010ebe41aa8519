"""The algebra behind the sparse-linear construction: cyclic shifts, circulants, and counts of sparse matrices."""

from __future__ import annotations

from itertools import product
from math import comb

from keyloom.functions.numtheory import is_prime, is_primitive_root

__all__ = ["circulant_det", "circulant_rank", "count_sparse", "full_rank_lower_bound", "full_rank_share_bound", "gl_order", "is_primitive_root", "nonzero_sum_bound", "nonzero_sum_count", "orbit_size", "rank", "spans_everything"]


def orbit_size(w: tuple[int, ...]) -> int:
    """How many different vectors the cyclic shifts of w are."""
    return len({w[i:] + w[:i] for i in range(len(w))})


def rank(rows: list[list[int]], p: int) -> int:
    rows, found = [list(r) for r in rows], 0
    for c in range(len(rows[0]) if rows else 0):
        pivot = next((i for i in range(found, len(rows)) if rows[i][c] % p), None)
        if pivot is None:
            continue
        rows[found], rows[pivot] = rows[pivot], rows[found]
        inverse = pow(rows[found][c], -1, p)
        rows[found] = [x * inverse % p for x in rows[found]]
        for i in range(len(rows)):
            if i != found and rows[i][c] % p:
                rows[i] = [(x - rows[i][c] * y) % p for x, y in zip(rows[i], rows[found])]
        found += 1
    return found


def circulant_rank(w: tuple[int, ...], p: int) -> int:
    """The dimension that the cyclic shifts of w span over the field of p elements."""
    return rank([list(w[i:] + w[:i]) for i in range(len(w))], p)


def circulant_det(w: tuple[int, ...], p: int) -> int:
    """The determinant of the matrix of all shifts, by elimination."""
    rows, value = [list(w[i:] + w[:i]) for i in range(len(w))], 1
    for c in range(len(w)):
        pivot = next((i for i in range(c, len(w)) if rows[i][c] % p), None)
        if pivot is None:
            return 0
        if pivot != c:
            rows[c], rows[pivot], value = rows[pivot], rows[c], -value
        value = value * rows[c][c] % p
        inverse = pow(rows[c][c], -1, p)
        for i in range(c + 1, len(w)):
            factor = rows[i][c] * inverse % p
            rows[i] = [(x - factor * y) % p for x, y in zip(rows[i], rows[c])]
    return value % p


def spans_everything(w: tuple[int, ...], p: int) -> bool:
    """The criterion for prime length q if p generates modulo q: the sum isn't 0 and the entries aren't all equal."""
    return sum(w) % p != 0 and len(set(w)) > 1


def count_sparse(n: int, s: int, r: int, p: int) -> int:
    """Matrices of r rows with exactly s of n entries other than 0."""
    return (comb(n, s) * (p - 1) ** s) ** r


def nonzero_sum_bound(s: int, p: int) -> int:
    """A lower bound for the vectors of s entries, none 0, whose sum isn't 0."""
    return (p - 1) ** s - (p - 1) ** (s - 1)


def nonzero_sum_count(s: int, p: int) -> int:
    """How many there are."""
    return (p - 1) * ((p - 1) ** s - (-1) ** s) // p


def brute_nonzero_sums(s: int, p: int) -> int:
    return sum(1 for v in product(range(1, p), repeat=s) if sum(v) % p)


def full_rank_lower_bound(q: int, s: int, r: int, p: int) -> float:
    """A lower bound for the s-sparse matrices of r rows and q columns that have full rank."""
    if not is_prime(q):
        raise ValueError("q must be a prime")
    value = 1.0
    for i in range(r):
        value *= comb(q, s) * nonzero_sum_bound(s, p) * (q - i) / q
    return value


def full_rank_share_bound(q: int, s: int, r: int, p: int) -> float:
    """The same as a share of all s-sparse matrices of that shape."""
    if not is_prime(q):
        raise ValueError("q must be a prime")
    value = 1.0
    for i in range(r):
        value *= (1 - 1 / (p - 1)) * (q - i) / q
    return value if s > 1 else 0.0


def gl_order(n: int, p: int) -> int:
    """Invertible n by n matrices over the field of p elements."""
    value = 1
    for i in range(n):
        value *= p**n - p**i
    return value
