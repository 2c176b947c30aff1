"""Hash functions and bijections as Column expressions; no Python runs per row."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

HALF = 1 << 20


def mulmod(a: Column, x: Column, p: Column | int) -> Column:
    """a*x mod p without leaving 63 bits, for a, x and p below 2^41: a goes in halves of 20 bits, whose products with x stay below 2^62."""
    p = p if isinstance(p, Column) else F.lit(p)
    high = F.pmod(F.pmod(F.shiftright(a, 20) * x, p) * F.lit(HALF), p)
    return F.pmod(high + F.pmod(a.bitwiseAND(F.lit(HALF - 1)) * x, p), p)


def two_universal(x: Column, a: Column, b: Column, p: int, size: int) -> Column:
    """((a*x + b) mod p) mod size."""
    return F.pmod(F.pmod(mulmod(a, x, p) + b, F.lit(p)), F.lit(size))


def four_universal(x: Column, coefficients: list[Column], p: int, size: int) -> Column:
    """A cubic polynomial mod p, by Horner's rule, folded into size."""
    out = coefficients[0]
    for c in coefficients[1:]:
        out = F.pmod(mulmod(x, out, p) + c, F.lit(p))
    return F.pmod(out, F.lit(size))


def two_universal_shift(x: Column, a: Column, bits: int) -> Column:
    """Multiply by an odd number modulo 2^32 and keep the high bits: no division. x and a below 2^32."""
    low, high = a.bitwiseAND(F.lit(0xFFFF)), F.shiftright(a, 16)
    product = (low * x + F.shiftleft((high * x).bitwiseAND(F.lit(0xFFFF)), 16)).bitwiseAND(F.lit(0xFFFFFFFF))
    return F.shiftright(product, 32 - bits)


def murmur(x: Column, seed: Column, size: int) -> Column:
    """Spark's Murmur3 of (seed, x), folded into size."""
    return F.pmod(F.hash(seed, x).cast("long"), F.lit(size))


def mix_bijection(x: Column, constants: list[tuple[int, int]], bits: int) -> Column:
    """A bijection of [0, 2^bits): rounds of odd*x + c, then xor with the high half. bits at most 31."""
    mask = F.lit((1 << bits) - 1)
    for odd, c in constants:
        x = (x * F.lit(odd) + F.lit(c)).bitwiseAND(mask)
        x = x.bitwiseXOR(F.shiftright(x, max(1, bits // 2)))
    return x


def feistel(x: Column, keys: list[int], bits: int) -> Column:
    """A bijection of [0, 2^bits), bits even: balanced Feistel rounds with a multiplicative round function."""
    half = bits // 2
    mask = F.lit((1 << half) - 1)
    left, right = F.shiftright(x, half), x.bitwiseAND(mask)
    for key in keys:
        mixed = F.shiftright(F.pmod(right * F.lit(key % (1 << 30) | 1) + F.lit(key % 65521), F.lit((1 << 61) - 1)), 7).bitwiseAND(mask)
        left, right = right, left.bitwiseXOR(mixed)
    return F.shiftleft(left, half).bitwiseOR(right)


def walk(size: int) -> tuple[int, int]:
    """Bits of the least domain of ``feistel`` that holds [0, size), and the steps after which a value is back inside but for a chance of 2^-60."""
    bits = max(2, (size - 1).bit_length())
    bits += bits % 2
    outside = 1 - size / (1 << bits)
    return bits, 0 if not outside else math.ceil(60 / -math.log2(outside))


def feistel_walk(x: Column, keys: list[int], size: int) -> Column:
    """A bijection of [0, size) for any size: the rounds are repeated while the value is outside."""
    bits, steps = walk(size)
    out = feistel(x, keys, bits)
    if not steps:
        return out
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), out, lambda v, _: F.when(v < size, v).otherwise(feistel(v, keys, bits)))


def md5_key(*parts) -> Column:
    return F.md5(F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts]))


def split_bins(q: Column, d: int) -> tuple[Column, Column]:
    """(bin, offset) of a position."""
    offset = F.pmod(q, F.lit(d))
    return F.call_function("div", q - offset, F.lit(d)), offset
