"""Arithmetic modulo the prime of the protocol, in DECIMAL columns and in Python integers.

Functions take the prime as ``p``; without it they take that of the enclosing ``with using(p)``, or the 61-bit one.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import Column
from pyspark.sql import functions as F

from .params import P61

_NARROW, _WIDE = "decimal(19,0)", "decimal(38,0)"
_PRIME: ContextVar[int] = ContextVar("prime", default=P61)
#: Wider primes are multiplied by limbs of so many bits.
_LIMB = 36


def modulus(p: int | None = None) -> int:
    return p or _PRIME.get()


@contextmanager
def using(p: int) -> Iterator[None]:
    """Columns that are built inside are modulo ``p``, of at most 80 bits."""
    if p.bit_length() > 80:
        raise ValueError("products of limbs must fit DECIMAL(38, 0)")
    token = _PRIME.set(p)
    try:
        yield
    finally:
        _PRIME.reset(token)


def whole(x: int) -> Column:
    """A constant of any size that DECIMAL(38, 0) holds."""
    return F.lit(str(x)).cast(_WIDE) if x >> 62 else F.lit(x).cast(_WIDE)


def reduce_(x: Column, p: int | None = None) -> Column:
    return F.pmod(x.cast(_WIDE), whole(modulus(p))).cast(_WIDE)


def constant(x: int, p: int | None = None) -> Column:
    return whole(x % modulus(p))


def add(a: Column, b: Column, p: int | None = None) -> Column:
    return reduce_(a + b, p)


def sub(a: Column, b: Column, p: int | None = None) -> Column:
    return reduce_(a - b, p)


def mul(a: Column, b: Column, p: int | None = None) -> Column:
    """Product of two reduced values.  Up to 61 bits it is below 2^122, so exact in DECIMAL(38, 0); wider values are
    multiplied limb by limb."""
    if modulus(p).bit_length() <= 61:
        return reduce_(a.cast(_NARROW) * b.cast(_NARROW), p)
    limb = F.lit(1 << _LIMB).cast("decimal(11,0)")
    low = F.pmod(a, F.lit(1 << _LIMB).cast(_WIDE)).cast("decimal(11,0)")
    high = ((a - low) / limb).cast("decimal(14,0)")
    times = lambda x, y: reduce_(x * y.cast("decimal(24,0)"), p)
    return reduce_(times(limb, times(high, b)) + times(low, b), p)


def power(a: Column, n: int, p: int | None = None) -> Column:
    """Square and multiply over the bits of a constant exponent."""
    bits = F.array(*[F.lit(c == "1") for c in bin(n)[2:]])
    return F.aggregate(bits, constant(1), lambda acc, bit: F.when(bit, mul(mul(acc, acc, p), a, p)).otherwise(mul(acc, acc, p)))


def inverse(a: Column, p: int | None = None) -> Column:
    return power(a, modulus(p) - 2, p)


def horner(coefficients: list[int], x: Column, p: int | None = None) -> Column:
    """Value of a polynomial with constant coefficients, lowest first."""
    return F.aggregate(F.array(*[constant(b, p) for b in reversed(coefficients)]), constant(0), lambda acc, b: add(mul(acc, x, p), b, p))


def decode_centered(x: Column, p: int | None = None) -> Column:
    """Residues above p/2 stand for negative values."""
    return F.when(x > whole(modulus(p) // 2), x - whole(modulus(p))).otherwise(x).cast("bigint")


def wrap_risk(sigma: float, d: int, m: int, w: int, p: int | None = None) -> float:
    """Bound of the chance that statistic plus noise leaves (-p/2, p/2): the Gaussian tail of the summed draws."""
    room = modulus(p) / 2 - m * w
    return 1.0 if room <= 0 else 2 * math.exp(-(room**2) / (2 * d * sigma**2))


def lookup_poly(k: int, p: int | None = None) -> list[int]:
    """Coefficients, lowest first, of the polynomial that is 0 at 1 and 1 at 2..k+1."""
    p = modulus(p)
    points = [(x, 0 if x == 1 else 1) for x in range(1, k + 2)]
    total = [0] * (k + 1)
    for i, (xi, yi) in enumerate(points):
        if not yi:
            continue
        basis, scale = [1], 1
        for j, (xj, _) in enumerate(points):
            if i != j:
                basis = [(a - xj * b) % p for a, b in zip([0, *basis], [*basis, 0], strict=True)]
                scale = scale * (xi - xj) % p
        factor = yi * pow(scale, -1, p)
        total = [(t + factor * b) % p for t, b in zip(total, basis, strict=True)]
    return total
