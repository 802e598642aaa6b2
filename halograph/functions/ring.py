"""Exact integer arithmetic on columns: features live modulo a prime, so sums do not depend on their order."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The prime that all ring features are reduced by.
PRIME = 1_000_003


def whole(c: Column, d: int | Column) -> Column:
    """c divided by d, cut to a whole number; both are used on non-negative numbers only."""
    return F.call_function("div", c, F.lit(d) if isinstance(d, int) else d)


def mod(c: Column) -> Column:
    return F.pmod(c, F.lit(PRIME).cast("long"))


def mul(*factors: Column) -> Column:
    """Product in the ring; each step is reduced so that no BIGINT overflows."""
    return reduce(lambda a, b: mod(a * b), factors)


def powers(c: Column, n: int) -> Column:
    """c + c**2 + ... + c**n in the ring, by Horner's rule."""
    out = c
    for _ in range(n - 1):
        out = mod(mod(out + 1) * c)
    return out


def pair_weight(d2: Column, cutoff: int) -> Column:
    """16 steps that fall with the squared distance and reach zero at the cutoff."""
    return whole((F.lit(cutoff * cutoff).cast("long") - d2) * 16, cutoff * cutoff)


def smooth_weight(d2: Column, cutoff: int) -> Column:
    """Value and slope vanish at the cutoff."""
    gap = whole(F.lit(cutoff * cutoff).cast("long") - d2, 1000)
    return mul(mod(gap), mod(gap))


class Ring:
    """Exact arithmetic modulo PRIME."""

    zero, one = staticmethod(lambda: F.lit(0).cast("long")), staticmethod(lambda: F.lit(1).cast("long"))
    mod, mul, powers = staticmethod(mod), staticmethod(mul), staticmethod(powers)
    kind = "long"


class Real:
    """The same formulas in doubles: nothing is reduced."""

    zero, one = staticmethod(lambda: F.lit(0.0)), staticmethod(lambda: F.lit(1.0))
    kind = "double"

    @staticmethod
    def mod(c: Column) -> Column:
        return c

    @staticmethod
    def mul(*factors: Column) -> Column:
        return reduce(lambda a, b: a * b, factors)

    @staticmethod
    def powers(c: Column, n: int) -> Column:
        return reduce(lambda a, _: (a + 1) * c, range(n - 1), c)


ARITHMETIC = {"ring": Ring, "real": Real}
