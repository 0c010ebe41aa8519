"""NumPy kernels over the keys of one shard or bucket."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from keyloom.functions.hashing import CHOICE, FIRST, MASK, SECOND, np_derived


class BuildError(ValueError):
    """Input that no seed can build, or seeds that ran out."""


def check_distinct(d0: np.ndarray, d1: np.ndarray, value: np.ndarray) -> None:
    """Equal digests give equal edges under every seed: found here, before any attempt."""
    order = np.lexsort((d1, d0))
    same = (d0[order][1:] == d0[order][:-1]) & (d1[order][1:] == d1[order][:-1])
    if same.any():
        at = int(np.nonzero(same)[0][0])
        kind = "repeated key" if value[order[at]] == value[order[at + 1]] else "conflicting values for one key"
        raise BuildError(f"{kind} (digest {d0[order[at]]})")


def endpoints(d0: np.ndarray, d1: np.ndarray, seed: int, n_slots: int, distinct: bool = True, family: str = "xx64") -> tuple[np.ndarray, np.ndarray]:
    """The two slots of each key."""
    u = np_derived(seed, FIRST, d0, d1, family) % n_slots
    h = np_derived(seed, SECOND, d0, d1, family)
    v = (u + 1 + h % (n_slots - 1)) % n_slots if distinct else h % n_slots
    return u, v


def masks(d0: np.ndarray, d1: np.ndarray, seed: int, modulus: int, family: str = "xx64") -> np.ndarray:
    return np_derived(seed, MASK, d0, d1, family) % modulus


def positions(d0: np.ndarray, d1: np.ndarray, seed: int, n_slots: int, r: int) -> np.ndarray:
    """r distinct slots of each key: one in each of r equal ranges; shape (r, n)."""
    ends = [n_slots * j // r for j in range(r + 1)]
    return np.stack([ends[j] + np_derived(seed, CHOICE + j, d0, d1) % (ends[j + 1] - ends[j]) for j in range(r)])


@dataclass
class Peeling:
    """Rounds of (keys, the slot by which each was taken); done: every key was."""

    rounds: list[tuple[np.ndarray, np.ndarray]]
    done: bool


def peel(slots: np.ndarray, n_slots: int) -> Peeling:
    """Takes keys away by slots that only one of those left has. ``slots``: (r, n). For r = 2 it ends exactly if the keys are a forest."""
    r, n = slots.shape
    degree = np.zeros(n_slots, np.int64)
    key_at = np.zeros(n_slots, np.int64)
    ids = np.arange(n)
    for row in slots:
        degree += np.bincount(row, minlength=n_slots)
        np.bitwise_xor.at(key_at, row, ids)
    rounds, left, scratch = [], n, np.zeros(n, np.int64)
    leaves = np.nonzero(degree == 1)[0]
    while len(leaves):
        at = _one_each(key_at[leaves], scratch)
        leaves = leaves[at]
        keys = key_at[leaves]
        rounds.append((keys, leaves))
        left -= len(keys)
        touched = slots[:, keys]
        for row in touched:
            np.subtract.at(degree, row, 1)
            np.bitwise_xor.at(key_at, row, keys)
        after = touched.ravel()
        leaves = after[degree[after] == 1]
    return Peeling(rounds, left == 0)


def _one_each(keys: np.ndarray, scratch: np.ndarray) -> np.ndarray:
    """Places of the last of each of some small numbers: what is written last stays."""
    places = np.arange(len(keys))
    scratch[keys] = places
    return scratch[keys] == places


def match_by_sorting(slots: np.ndarray, n_slots: int) -> Peeling:
    """What ``peel`` gives, by a matching in rounds: each sorts the slots of all keys that are left and takes those keys that have one to themselves."""
    r, n = slots.shape
    left, rounds, scratch = np.arange(n), [], np.zeros(n, np.int64)
    while len(left):
        flat = slots[:, left].ravel()
        order = np.argsort(flat, kind="stable")
        ranked = flat[order]
        differs = np.concatenate(([True], ranked[1:] != ranked[:-1], [True]))
        alone = order[differs[:-1] & differs[1:]]
        if not len(alone):
            return Peeling(rounds, False)
        alone = alone[_one_each(alone % len(left), scratch)]
        rounds.append((left[alone % len(left)], flat[alone]))
        left = np.delete(left, alone % len(left))
    return Peeling(rounds, True)


def is_forest(u: np.ndarray, v: np.ndarray, n_slots: int) -> Peeling | None:
    """The peeling of a graph without loops, repeated edges and cycles; None for any other. Peeling stops at a repeated edge as at any cycle."""
    if (u == v).any():
        return None
    peeled = peel(np.stack((u, v)), n_slots)
    return peeled if peeled.done else None


@dataclass
class Forest:
    """Slots solved so that g(u) + g(v) = rhs; ``component``: the least slot of each slot's tree, where g is 0."""

    g: np.ndarray
    component: np.ndarray
    sizes: np.ndarray


def solve_forest(peeled: Peeling, u: np.ndarray, v: np.ndarray, rhs: np.ndarray, n_slots: int, modulus: int) -> Forest:
    """Goes back through the rounds; then moves each tree so that its least slot holds 0, which makes the table canonical."""
    g, root, odd = np.zeros(n_slots, np.int64), np.arange(n_slots), np.zeros(n_slots, bool)
    for keys, leaf in reversed(peeled.rounds):
        other = u[keys] ^ v[keys] ^ leaf
        g[leaf] = (rhs[keys] - g[other]) % modulus
        root[leaf], odd[leaf] = root[other], ~odd[other]
    least, falling = np.zeros(n_slots, np.int64), np.arange(n_slots - 1, -1, -1)
    least[root[::-1]] = falling  # what is written last stays: the least slot of each root
    first = least[root]
    move = g[first]
    g = np.where(odd == odd[first], g - move, g + move) % modulus
    sizes = np.bincount(first, minlength=n_slots)
    return Forest(g, first, sizes)


def settle_forest(peeled: Peeling, u: np.ndarray, v: np.ndarray, rhs: np.ndarray, n_slots: int, modulus: int) -> np.ndarray:
    """Slots that solve the forest, each tree with 0 at the slot that peeling left last; less work than ``solve_forest``, and not canonical."""
    g, ends = np.zeros(n_slots, np.int64), u ^ v
    for keys, leaf in reversed(peeled.rounds):
        g[leaf] = (rhs[keys] - g[ends[keys] ^ leaf]) % modulus
    return g


def shift_side(u: list[int], v: list[int], g: dict[int, int], edge: int, new_rhs: int, modulus: int) -> dict[int, int]:
    """The slots that change if one edge of a tree gets a new right-hand side and only its smaller side moves."""
    near: dict[int, list[int]] = {}
    for i, (a, b) in enumerate(zip(u, v)):
        if i != edge:
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)

    def side(start: int) -> dict[int, int]:
        sign, left = {start: 1}, [start]
        while left:
            x = left.pop()
            for y in near.get(x, ()):
                if y not in sign:
                    sign[y] = -sign[x]
                    left.append(y)
        return sign

    change = new_rhs - g[u[edge]] - g[v[edge]]
    smaller = min((side(u[edge]), side(v[edge])), key=lambda s: (len(s), min(s)))
    return {x: (g[x] + sign * change) % modulus for x, sign in smaller.items()}


def fill_two_tables(peeled: Peeling, slots: np.ndarray, value: np.ndarray, mask: np.ndarray, n_slots: int) -> tuple[np.ndarray, np.ndarray]:
    """The table whose cells at a key's slots, combined with its mask, tell which slot is its own, and the table of values there."""
    choice, content = np.zeros(n_slots, np.int64), np.zeros(n_slots, np.int64)
    for keys, own in reversed(peeled.rounds):
        of = slots[:, keys]
        which = (of == own).argmax(axis=0)
        content[own] = value[keys]
        others = np.bitwise_xor.reduce(choice[of], axis=0) ^ choice[own]
        choice[own] = which ^ mask[keys] ^ others
    return choice, content


def solve_peeled(peeled: Peeling, slots: np.ndarray, rhs: np.ndarray, n_slots: int, modulus: int) -> np.ndarray:
    """Slots so that each key's r of them add up to its rhs: back through the rounds, each key settles the slot that was its own."""
    g = np.zeros(n_slots, np.int64)
    for keys, own in reversed(peeled.rounds):
        rest = g[slots[:, keys]].sum(axis=0) - g[own]
        g[own] = (rhs[keys] - rest) % modulus
    return g


def mul_mod(a: np.ndarray, b: np.ndarray, p) -> np.ndarray:
    """Products of residues modulo p (below 2^61; a number or an array). Above 2^31 the quotient comes from extended precision, and the rest wraps to what is left."""
    if int(np.max(p, initial=0)) < 1 << 31:
        return a * b % p
    if np.finfo(np.longdouble).nmant < 63:  # no extended precision on this machine
        return (a.astype(object) * b % np.asarray(p, object)).astype(np.int64)
    quotient = (a.astype(np.longdouble) * b / np.asarray(p, np.longdouble)).astype(np.int64)
    with np.errstate(over="ignore"):
        rest = a * b - quotient * p
    rest = np.where(rest < 0, rest + p, rest)
    return np.where(rest >= p, rest - p, rest)


def sum_mod(x: np.ndarray, axis: int, p) -> np.ndarray:
    """Sums of residues modulo p, in two halves so that none overflows."""
    if int(np.max(p, initial=0)) < 1 << 31:
        return x.sum(axis=axis) % p
    low, high = (x & ((1 << 30) - 1)).sum(axis=axis), (x >> 30).sum(axis=axis)
    return (mul_mod(high % p, np.int64(1 << 30) % p, p) + low % p) % p


class Echelon:
    """Reduced rows over a prime field below 2^61, with a right-hand side as the last column; rows are added one by one."""

    def __init__(self, width: int, p: int):
        self.width, self.p = width, p
        self.rows = np.zeros((0, width + 1), np.int64)
        self.pivots: list[int] = []

    def try_add(self, row: np.ndarray) -> bool:
        """Adds a row (width + 1 residues) if it is independent of those there."""
        p = self.p
        if self.pivots:
            row = (row - sum_mod(mul_mod(row[self.pivots][:, None], self.rows, p), 0, p)) % p
        filled = np.nonzero(row[:-1])[0]
        if not len(filled):
            return False
        pivot = int(filled[0])
        row = mul_mod(row, np.int64(pow(int(row[pivot]), -1, p)), p)
        if self.pivots:
            self.rows = (self.rows - mul_mod(self.rows[:, pivot][:, None], row, p)) % p
        self.rows = np.vstack((self.rows, row))
        self.pivots.append(pivot)
        return True

    def solution(self) -> np.ndarray:
        """One solution; unknowns without a pivot are 0."""
        g = np.zeros(self.width, np.int64)
        g[self.pivots] = self.rows[:, -1]
        return g


class Echelons:
    """Many small systems at once, each over its own prime: the same steps as ``Echelon``, on arrays (system, row, column) padded to the widest."""

    def __init__(self, widths: np.ndarray, p: np.ndarray, most_rows: int):
        self.widths, self.p, self.width = widths, p, int(widths.max(initial=1))
        self.rows = np.zeros((len(widths), most_rows, self.width + 1), np.int64)
        self.pivots = np.full((len(widths), most_rows), -1, np.int64)
        self.held = np.zeros(len(widths), np.int64)

    def try_add(self, at: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Adds one row to each of the systems ``at``; which of them were independent."""
        most = int(self.held[at].max(initial=0))
        p = self.p[at][:, None]
        if most:
            have, pivots = self.rows[at, :most], self.pivots[at, :most]
            factor = np.where(pivots >= 0, np.take_along_axis(rows, np.maximum(pivots, 0), axis=1), 0)
            rows = (rows - sum_mod(mul_mod(factor[:, :, None], have, p[:, :, None]), 1, p)) % p
        filled = rows[:, :-1] != 0
        good = filled.any(axis=1)
        if not good.any():
            return good
        at, rows, p = at[good], rows[good], p[good]
        pivot = filled[good].argmax(axis=1)
        lead = rows[np.arange(len(at)), pivot]
        inverse = np.array([pow(x, -1, q) for x, q in zip(lead.tolist(), p[:, 0].tolist())], np.int64)
        rows = mul_mod(rows, inverse[:, None], p)
        if most:
            have = self.rows[at, :most]
            factor = np.take_along_axis(have, pivot[:, None, None], axis=2)
            self.rows[at, :most] = (have - mul_mod(factor, rows[:, None, :], p[:, :, None])) % p[:, :, None]
        nth = self.held[at]
        self.rows[at, nth], self.pivots[at, nth] = rows, pivot
        self.held[at] = nth + 1
        return good

    def solutions(self) -> list[np.ndarray]:
        """One solution of each system."""
        out = []
        for width, rows, pivots, held in zip(self.widths.tolist(), self.rows, self.pivots, self.held.tolist()):
            g = np.zeros(width, np.int64)
            g[pivots[:held]] = rows[:held, -1]
            out.append(g)
        return out


class XorRows:
    """The same over GF(2): rows are whole numbers of bits, right-hand sides are words."""

    def __init__(self, width: int):
        self.width = width
        self.rows: dict[int, tuple[int, int]] = {}

    def try_add(self, bits: int, rhs: int) -> bool:
        while bits:
            pivot = bits.bit_length() - 1
            if pivot not in self.rows:
                self.rows[pivot] = (bits, rhs)
                return True
            have, other = self.rows[pivot]
            bits, rhs = bits ^ have, rhs ^ other
        return False

    def solution(self) -> np.ndarray:
        g = [0] * self.width
        for pivot in sorted(self.rows):
            bits, rhs = self.rows[pivot]
            bits ^= 1 << pivot
            while bits:
                low = bits & -bits
                rhs ^= g[low.bit_length() - 1]
                bits ^= low
            g[pivot] = rhs
        return np.array(g, np.int64)
