"""Exact laws behind the sketches, in integers and fractions on the driver; sizes are those of one experiment.

Notation: D universe, K bins of width d = D/K, f elements in the union of two sets, a in both, m bins that
hold an element of the union. A bin of the union has f1 elements, a1 of them in both sets.
"""

from __future__ import annotations

import random
from collections.abc import Callable
from fractions import Fraction
from functools import lru_cache
from itertools import combinations, permutations
from math import comb


def choose(n: int, k: int) -> int:
    return comb(n, k) if 0 <= k <= n else 0


@lru_cache(None)
def occupied_ways(k: int, n: int, d: int) -> int:
    """Ways to put n points into k bins of width d with no bin empty."""
    if k == 0:
        return int(n == 0)
    if k == 1:
        return choose(d, n) if n > 0 else 0
    return sum(choose(d, j) * occupied_ways(k - 1, n - j, d) for j in range(max(1, n - (k - 1) * d), min(d, n - k + 1) + 1))


def bin_law(D: int, K: int, f: int, a: int, m: int) -> dict[tuple[int, int], Fraction]:
    """Law of (a1, f1) in one occupied bin, given m occupied bins."""
    d, out = D // K, {}
    whole = occupied_ways(m, f, d)
    for f1 in range(1, min(d, f) + 1):
        ways = choose(d, f1) * occupied_ways(m - 1, f - f1, d)
        if ways:
            for a1 in range(max(0, f1 - (f - a)), min(a, f1) + 1):
                share = Fraction(choose(a, a1) * choose(f - a, f1 - a1), choose(f, f1))
                out[a1, f1] = Fraction(ways, whole) * share
    return out


def empty_bins_pmf(D: int, K: int, f: int) -> list[Fraction]:
    """P(j of the K bins are empty), j = 0..K."""
    d, whole = D // K, comb(D, f)
    return [Fraction(choose(K, j) * sum((-1) ** t * choose(K - j, t) * choose((K - j - t) * d, f) for t in range(K - j + 1)), whole) for j in range(K + 1)]


@lru_cache(None)
def pair_collision(a: int, f: int, d: int) -> Fraction:
    """P(two slots both collide on one bin of width d with f elements, a in both sets), if the slots' turns of one permutation differ by one.

    The sum runs over how many places of each kind (in both sets, in one, in neither) follow on places of
    each kind around the bin. Exact for turns whose difference has no factor in common with d.
    """
    if a == 0:
        return Fraction(0)
    if a == f:
        return Fraction(1)
    if f == d:
        return Fraction(a * (a - 1), f * (f - 1))
    one, none = f - a, d - f
    whole, total = choose(d - a - 1, none - 1) * choose(d - 1, a), Fraction(0)
    for l0 in range(a + 1):
        for l2 in range(min(none, a - l0) + 1):
            l1 = a - l0 - l2
            for g0 in range(min(none, a - l0) + 1):
                for g1 in range(min(none - g0, one - l1) + 1):
                    g2, h0, h1 = none - g0 - g1, a - l0 - g0, one - l1 - g1
                    h2 = one - h0 - h1
                    if min(g2, h0, h1, h2) < 0 or l2 + g2 + h2 != none:
                        continue
                    ways = 0
                    for s in range(none):
                        t = none - s - g1
                        ways += choose(none, s) * choose(one - 1, none - s - 1) * choose(s, g0 - t) * choose(none - s, t) * choose(none - s, l2 - g0 + t) * choose(one - none + s, l1 - t) * choose(a - 1, a - l1 - l2)
                    if ways:
                        reach = f + g0 + g1
                        total += (Fraction(l0, reach) + Fraction(a * (g0 + l2), reach * f)) * ways
    return total / whole


def pair_collision_brute(a: int, f: int, d: int, gap: int = 1) -> Fraction:
    """The same by listing all placements and all permutations; d at most 7."""
    total, n = 0, 0
    orders = list(permutations(range(d)))
    for union in combinations(range(d), f):
        for both in combinations(union, a):
            for pi in orders:
                first = min(union, key=lambda x: pi[x])
                second = min(union, key=lambda x: pi[(x - gap) % d])
                total += first in both and second in both
                n += 1
    return Fraction(total, n)


def pair_collision_mc(a: int, f: int, d: int, runs: int, seed: int = 1, gap: int = 1) -> float:
    """The same by simulation."""
    rng, hits = random.Random(seed), 0
    for _ in range(runs):
        pi = rng.sample(range(d), d)
        union = rng.sample(range(d), f)
        both = set(union[:a])
        hits += min(union, key=lambda x: pi[x]) in both and min(union, key=lambda x: pi[(x - gap) % d]) in both
    return hits / runs


def _variance(D: int, K: int, f: int, a: int, joint: Callable[[int, int, int], Fraction]) -> Fraction:
    if D % K or not 0 <= a <= f <= D or f < 1:
        raise ValueError("K divides D and 0 <= a <= f <= D")
    if K * K > D:
        raise ValueError("the law needs K*K <= D")
    d, J = D // K, Fraction(a, f)
    other = Fraction(a - 1, f - 1) if f > 1 else Fraction(0)
    second = Fraction(0)
    for empty, weight in enumerate(empty_bins_pmf(D, K, f)):
        m = K - empty
        if not weight or not m:
            continue
        own = sum((p * joint(a1, f1, d) for (a1, f1), p in bin_law(D, K, f, a, m).items()), Fraction(0)) if empty else Fraction(0)
        refilled = own / m + Fraction(m - 1, m) * J * other
        second += weight * (K * J + empty * (2 * K - empty - 1) * refilled + m * (m - 1) * J * other)
    return second / K**2 - J**2


def var_rotating(D: int, K: int, f: int, a: int) -> Fraction:
    """Variance of the estimator of rotating binned MinHash, M = K and K*K <= D."""
    return _variance(D, K, f, a, pair_collision)


def var_fresh(D: int, K: int, f: int, a: int) -> Fraction:
    """Variance with a fresh permutation per slot: two slots on one bin collide independently."""
    return _variance(D, K, f, a, lambda a1, f1, d: Fraction(a1, f1) ** 2)


def var_standard(K: int, f: int, a: int) -> Fraction:
    """Variance of standard MinHash."""
    J = Fraction(a, f)
    return J * (1 - J) / K


def var_rot(D: int, K: int, f: int, a: int) -> Fraction:
    """Variance of rotating MinHash with an initial shuffle."""
    J = Fraction(a, f)
    return J / K + Fraction(K - 1, K) * pair_collision(a, f, D) - J**2


def variance_ratio(D: int, K: int, f: int, a: int) -> Fraction:
    """How many times the variance of fresh permutations that of the rotating one is taken."""
    return var_fresh(D, K, f, a) / var_rotating(D, K, f, a)
