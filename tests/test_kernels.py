"""Kernels, hashing, packing and algebra, without Spark where it isn't needed."""

import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from keyloom.functions import algebra, hashing, numtheory, packing
from keyloom.operators import kernels as K
from keyloom.operators import measures as M
from keyloom.plans import params


def test_numpy_hash_equals_catalyst(spark):
    numbers = [0, 1, -1, 2**63 - 1, -(2**63), 42, 10**12]
    rows = spark.createDataFrame([(a, b) for a in numbers for b in numbers], "d0 long, d1 long")
    for family in hashing.FAMILIES[:1] + hashing.FAMILIES[2:]:
        own = rows.where("d0 >= 0 and d0 < 2147483647") if family == "two_universal" else rows
        got = own.select("d0", "d1", hashing.derived(F.lit(7).cast("long"), 3, family).alias("h")).collect()
        a, b = (np.array([r[c] for r in got], np.int64) for c in ("d0", "d1"))
        assert hashing.np_derived(7, 3, a, b, family).tolist() == [r["h"] for r in got]


def test_key_types(spark):
    with pytest.raises(TypeError):
        hashing.check_key_types(spark.createDataFrame([(1.0,)], "k double"), "k")
    texts = spark.createDataFrame([("",), ("é",), ("x" * 100_000,)], "k string")
    assert hashing.with_digest(texts, "k").select("d0", "d1").distinct().count() == 3


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 61), st.data())
def test_packing_round_trip(width, data):
    values = np.array(data.draw(st.lists(st.integers(0, 2**width - 1), max_size=40)), np.int64)
    packed = packing.pack(values, width)
    assert len(packed) == math.ceil(len(values) * width / 8)
    assert packing.unpack(packed, width, len(values)).tolist() == values.tolist()
    if len(values):
        assert packing.gather(packed, width, np.array([len(values) - 1, 0])).tolist() == [values[-1], values[0]]


GRAPHS = {
    "path": ([(0, 1), (1, 2), (2, 3)], True),
    "star": ([(0, 1), (0, 2), (0, 3)], True),
    "loop": ([(1, 1)], False),
    "double edge": ([(0, 1), (1, 0)], False),
    "triangle": ([(0, 1), (1, 2), (2, 0)], False),
    "two trees": ([(0, 1), (2, 3), (3, 4)], True),
    "tree and cycle": ([(0, 1), (2, 3), (3, 4), (4, 5), (5, 2)], False),
}


@pytest.mark.parametrize("name", GRAPHS)
def test_forest_test(name):
    graph, expected = GRAPHS[name]
    u, v = np.array(graph).T
    assert (K.is_forest(u, v, 6) is not None) == expected


def example():
    u, v, mask, f = np.array([0, 3, 6]), np.array([3, 5, 7]), np.array([4, 9, 2]), np.array([1, 0, 1])
    return u, v, mask, f, (f - mask) % 16


def test_worked_acyclic_example():
    u, v, mask, f, rhs = example()
    assert rhs.tolist() == [13, 7, 15]
    g = K.solve_forest(K.is_forest(u, v, 8), u, v, rhs, 8, 16).g
    assert g.tolist() == [0, 0, 0, 13, 0, 10, 0, 15]
    assert ((g[u] + g[v] + mask) % 16).tolist() == f.tolist()
    assert (g[1] + g[2] + 7) % 16 >= 2 and (g[1] + g[2] + 1) % 16 == 1


def test_worked_update_example():
    u, v, mask, f, rhs = example()
    new = (np.array([0, 0, 1]) - mask) % 16
    g = K.solve_forest(K.is_forest(u, v, 8), u, v, new, 8, 16).g
    assert g.tolist() == [0, 0, 0, 12, 0, 11, 0, 15]
    assert K.shift_side([0, 3], [3, 5], {0: 0, 3: 13, 5: 10}, 0, 12, 16) == {0: 15}


@pytest.mark.parametrize("modulus", [2, 7, 9, 16, 1000, 2**40, 3**30])
def test_equations_hold_in_every_ring(modulus):
    g = np.random.default_rng(modulus % 97)
    keys = np.arange(300)
    for seed in range(50):
        u, v = K.endpoints(keys, keys, seed, 750)
        if peeled := K.is_forest(u, v, 750):
            break
    rhs = g.integers(0, modulus, 300)
    forest = K.solve_forest(peeled, u, v, rhs, 750, modulus)
    assert ((forest.g[u] + forest.g[v]) % modulus == rhs).all() and (forest.g[forest.component] == 0).all()
    assert (forest.component <= np.arange(750)).all() and forest.sizes.sum() == 750


@pytest.mark.parametrize("c, distinct", [(2.09, True), (2.5, True), (3.0, True), (2.5, False)])
def test_acyclic_rate_near_formula(c, distinct):
    found = M.acyclic_rate(2_000, c, 300, distinct)
    assert abs(found["rate"] - found["formula"]) < 0.1
    assert found["mean_max_component"] <= found["max_component"] <= params.component_bound(2_000, c)


@pytest.mark.parametrize("r", [2, 3])
def test_both_matchings_end_alike(r):
    keys = np.arange(400)
    for seed in range(20):
        at = K.positions(keys, keys, seed, 1000, r)
        a, b = K.peel(at, 1000), K.match_by_sorting(at, 1000)
        assert a.done == b.done and [sorted(x.tolist()) for x, _ in a.rounds] == [sorted(x.tolist()) for x, _ in b.rounds]


@pytest.mark.parametrize("r", [2, 3])
def test_two_tables(r):
    keys = np.arange(500)
    value = keys % 31
    for seed in range(64):
        at = K.positions(keys, keys, seed, 1250, r)
        if (peeled := K.match_by_sorting(at, 1250)).done:
            break
    mask = K.masks(keys, keys, seed, 1 << 20)
    choice, content = K.fill_two_tables(peeled, at, value, mask, 1250)
    which = np.bitwise_xor.reduce(choice[at], axis=0) ^ mask
    assert (which < r).all() and (content[at[which, keys]] == value).all()
    assert len(set(at[which, keys].tolist())) == 500


def test_worked_sparse_example():
    rows = K.Echelon(3, 5)
    assert rows.try_add(np.array([2, 1, 0, 3])) and not rows.try_add(np.array([4, 2, 0, 4])) and rows.try_add(np.array([0, 1, 3, 4]))
    assert rows.solution().tolist() == [2, 4, 0]


@settings(max_examples=60, deadline=None)
@given(st.sampled_from([2, 3, 5, 7]), st.lists(st.lists(st.integers(0, 6), min_size=5, max_size=5), max_size=8))
def test_echelon_rank(p, matrix):
    rows, kept = K.Echelon(5, p), []
    for row in matrix:
        row = [x % p for x in row]
        before = algebra.rank(kept, p)
        grows = algebra.rank([*kept, row], p) > before
        assert rows.try_add(np.array([*row, sum(row) % p])) == grows
        if grows:
            kept.append(row)
    g = rows.solution()
    assert all((np.array(row) @ g - sum(row)) % p == 0 for row in kept)


def test_xor_rows():
    rows = K.XorRows(4)
    assert rows.try_add(0b0011, 5) and rows.try_add(0b0110, 9) and not rows.try_add(0b0101, 1)
    g = rows.solution()
    assert g[0] ^ g[1] == 5 and g[1] ^ g[2] == 9


def test_repeated_and_conflicting_keys():
    d = np.array([1, 2, 1])
    with pytest.raises(K.BuildError, match="repeated"):
        K.check_distinct(d, d, np.array([4, 5, 4]))
    with pytest.raises(K.BuildError, match="conflicting"):
        K.check_distinct(d, d, np.array([4, 5, 6]))


def order(a, q):
    x, n = a % q, 1
    while x != 1:
        x, n = x * a % q, n + 1
    return n


@pytest.mark.parametrize("q", [5, 13, 53, 101])
def test_generator_test(q):
    assert [a for a in range(1, q) if numtheory.is_primitive_root(a, q)] == [a for a in range(1, q) if order(a, q) == q - 1]


def test_the_printed_generator_test_is_wrong():
    """Raising to the prime factors themselves accepts residues that don't generate."""
    wrong = [a for a in range(2, 13) if all(pow(a, f, 13) != 1 for f in numtheory.prime_factors(12)) and order(a, 13) != 12]
    assert wrong


@pytest.mark.parametrize("method", ["direct", "list"])
@pytest.mark.parametrize("n, eps, bits", [(5, 0.1, 8), (50, 0.1, 31), (200, 0.05, 31), (300, 0.5, 20)])
def test_primes(method, n, eps, bits):
    found = numtheory.choose_primes(n, eps, bits, 1, method)
    assert numtheory.is_prime(found.q) and not any(numtheory.is_prime(x) for x in range(max(3, math.ceil(n * (1 + eps))), found.q))
    assert numtheory.is_prime(found.p) and found.p.bit_length() == bits and order(found.p, found.q) == found.q - 1


def test_miller_rabin():
    sieve = [n for n in range(2, 2000) if all(n % d for d in range(2, int(n**0.5) + 1))]
    assert [n for n in range(2000) if numtheory.is_prime(n)] == sieve
    assert not numtheory.is_prime(3215031751) and numtheory.is_prime(2**61 - 1)


@pytest.mark.parametrize("q, p, mismatches", [(5, 2, False), (5, 3, False), (7, 3, False), (3, 5, False), (7, 2, True)])
def test_cyclic_span(q, p, mismatches):
    from itertools import product

    wrong = sum((algebra.circulant_rank(w, p) == q) != algebra.spans_everything(w, p) for w in product(range(p), repeat=q))
    assert (wrong > 0) == mismatches and numtheory.is_primitive_root(p, q) != mismatches


def test_alternating_vector_and_orbits():
    assert algebra.circulant_rank((1, 0, 1, 0, 1, 0), 5) == 2 and algebra.orbit_size((1, 0, 1, 0, 1, 0)) == 2
    assert algebra.orbit_size((1, 0, 0, 2, 0)) == 5
    assert (algebra.circulant_det((1, 2, 0), 5) != 0) == (algebra.circulant_rank((1, 2, 0), 5) == 3)


def test_counts():
    for p in (3, 5, 7):
        for s in (1, 2, 3):
            exact = algebra.brute_nonzero_sums(s, p)
            assert algebra.nonzero_sum_count(s, p) == exact >= algebra.nonzero_sum_bound(s, p)
            assert (exact == algebra.nonzero_sum_bound(s, p)) == (s == 2)
    assert algebra.gl_order(2, 2) == 6 and algebra.count_sparse(4, 2, 1, 3) == 24
    rate = M.full_rank_rate(4, 5, 2, 3, 300)
    assert rate >= algebra.full_rank_lower_bound(5, 2, 4, 3) / algebra.count_sparse(5, 2, 4, 3) - 0.1


def test_parameters():
    for bad in (lambda: params.check_c(2.0), lambda: params.modulus_for(4, 8, 0.1), lambda: params.modulus_for(40, None, 2.0**-40), lambda: params.check_k(0), lambda: params.bucket_tail(10, 2, 4.0)):
        with pytest.raises(ValueError):
            bad()
    assert params.modulus_for(5, None, 2.0**-32) == 2**37
    assert params.acyclic_probability(2.09) == pytest.approx(0.335, abs=0.001)


def test_products_of_wide_residues():
    r = random.Random(4)
    for p in (2**31 - 1, 2**61 - 1, (1 << 60) + 33, 10**15 + 37):
        a, b = ([r.randrange(p) for _ in range(200)] + [p - 1, 0, 1] for _ in range(2))
        assert K.mul_mod(np.array(a), np.array(b), p).tolist() == [x * y % p for x, y in zip(a, b)]
        assert int(K.sum_mod(np.array(a)[:, None], 0, p)[0]) == sum(a) % p


def test_many_systems_equal_single_ones():
    g = np.random.default_rng(3)
    widths, primes = np.array([5, 7, 11, 3]), np.array([101, 2**31 - 1, 97, 2**30 + 3])
    many, single = K.Echelons(widths, primes, 12), [K.Echelon(int(w), int(p)) for w, p in zip(widths, primes)]
    for _ in range(12):
        at = np.flatnonzero(g.random(4) < 0.8)
        rows = np.zeros((len(at), many.width + 1), np.int64)
        for i, b in enumerate(at):
            rows[i, g.integers(0, widths[b], 2)] = g.integers(1, primes[b])
            rows[i, -1] = g.integers(0, primes[b])
        expected = [single[b].try_add(np.concatenate((rows[i, : widths[b]], rows[i, -1:]))) for i, b in enumerate(at)]
        assert many.try_add(at, rows).tolist() == expected
    assert [x.tolist() for x in many.solutions()] == [x.solution().tolist() for x in single]
