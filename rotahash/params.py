"""Parameters of the sketches and the numbers derived from a seed, the same in every engine."""

from __future__ import annotations

import hashlib
import math
import warnings
from dataclasses import dataclass, replace

#: Largest table that may be broadcast for lookups, in rows.
BROADCAST_ROWS = 1 << 22


def digest(*parts) -> int:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest(), 16)


def short(*parts) -> int:
    """The first 32 bits of the digest."""
    return digest(*parts) >> 96


def is_prime(n: int) -> bool:
    """Deterministic below 3.3e24."""
    if n < 2:
        return False
    small = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37, 41)
    for q in small:
        if n % q == 0:
            return n == q
    s, odd = 0, n - 1
    while odd % 2 == 0:
        s, odd = s + 1, odd // 2
    for a in small:
        x = pow(a, odd, n)
        if x in (1, n - 1):
            continue
        for _ in range(s - 1):
            x = x * x % n
            if x == n - 1:
                break
        else:
            return False
    return True


def next_prime(n: int) -> int:
    """The smallest prime above n."""
    n += 1
    while not is_prime(n):
        n += 1
    return n


@dataclass(frozen=True)
class SketchParams:
    """What a sketch is made of.

    D: size of the universe; elements are 0..D-1. K: bins (or permutations). M: slots, K by default.
    split: how an element becomes a position - 'perm', '2u', '4u', 'murmur', 'mix', 'identity'.
    inner: how a position is ranked in a slot of standard or rotating MinHash - 'perm', '2u', '4u', 'murmur'.
    fill: 'none', 'copy', 'fresh' or 'rotate'. donor: 'clockwise', 'two_way' or 'uniform'.
    first_scan: 'rotate' reads bin s mod K in slot s, 'random' a bin drawn per slot.
    shift: extra rotation of slot s - 'plain', 'per_round', 'per_cycle' or 'lcm'.
    share: one stored permutation for the split and the ranks. implicit: the split's own order serves the first scan.
    copy_offset: copies from distance t are moved by t*(D+1), so copies over different distances never match.
    """

    D: int
    K: int
    M: int | None = None
    seeds: tuple[int, ...] = (42,)
    split: str = "perm"
    inner: str = "perm"
    first_scan: str = "rotate"
    donor: str = "uniform"
    fill: str = "rotate"
    shift: str = "plain"
    share: bool = False
    implicit: bool = False
    copy_offset: bool = False
    attempts: int = 64

    def __post_init__(self):
        if self.K < 1 or self.slots < 1 or self.D < 1 or not self.seeds:
            raise ValueError("D, K, M and the number of seeds are at least 1")
        if self.D % self.K:
            raise ValueError("K divides D; pad the universe with SketchParams.padded")
        if self.fill == "rotate" and self.shift == "plain" and self.K * self.slots > self.D:
            warnings.warn("a bin is read with one rotation twice when K*M > D; set shift", stacklevel=3)
        if self.split == "mix" and self.D & (self.D - 1):
            raise ValueError("the bijective mixer needs a power of two")

    @classmethod
    def padded(cls, D: int, K: int, **options) -> SketchParams:
        """The universe padded with zeros to a multiple of K; no row is written for a zero."""
        return cls(-(-D // K) * K, K, **options)

    @property
    def slots(self) -> int:
        return self.K if self.M is None else self.M

    @property
    def d(self) -> int:
        return self.D // self.K

    def with_(self, **options) -> SketchParams:
        return replace(self, **options)

    def bin_of(self, slot: int, seed: int) -> int:
        """Bin that slot reads in the first scan."""
        return slot % self.K if self.first_scan == "rotate" else short(seed, "scan", slot) % self.K

    def probe(self, slot: int, attempt: int, seed: int) -> int:
        return short(seed, "probe", slot, attempt) % self.K

    def coin(self, slot: int, seed: int) -> int:
        """+1: to the right, -1: to the left."""
        return 1 if short(seed, "coin", slot) % 2 else -1

    def rotation(self, slot: int) -> int:
        """How far slot turns the permutation: its number from 1 on, and the extra shift."""
        n = slot + 1
        extra = {"plain": 0, "per_round": n // self.K, "per_cycle": n // self.d, "lcm": slot // math.lcm(self.K, self.d)}[self.shift]
        return n + extra

    def linear(self, seed: int, tag: str = "2u", size: int | None = None) -> tuple[int, int, int]:
        """(a, b, p) of a 2-universal hash into ``size``: a odd, p the smallest prime above."""
        p = next_prime(size or self.D)
        a = digest(seed, tag, "a") % (p - 1) + 1
        return (a if a % 2 else (a + 1) % p or 1), digest(seed, tag, "b") % p, p

    def cubic(self, seed: int, tag: str = "4u", size: int | None = None) -> tuple[int, int, int, int, int]:
        """Coefficients, highest first, and the prime of a 4-universal hash."""
        p = next_prime(size or self.D)
        return (digest(seed, tag, 3) % (p - 1) + 1, *(digest(seed, tag, i) % p for i in (2, 1, 0)), p)

    def budget(self, method: str) -> int:
        """Length of the permutations a method stores."""
        D, d, K, M = self.D, self.d, self.K, self.slots
        split = D if self.split == "perm" else 0
        return {
            "std": K * D,
            "rot": split if self.share else split + (D if self.inner == "perm" else 0),
            "bin": split,
            "copy": split,
            "fresh": split + max(0, M - K) * d if split else M * d,
            "rotbin": split if self.share else split + d,
        }[method]
