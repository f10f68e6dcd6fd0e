"""Hash families as column expressions."""

from __future__ import annotations

import random

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The prime 2^31 - 1: products of two residues stay below 2^62.
PRIME = 2147483647
LOW30 = (1 << 30) - 1


def md5_60(text: Column) -> Column:
    """The leading 60 bits of the MD5 digest as a long; every engine gives the same."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def uniform(*parts: Column) -> Column:
    """A non-negative long drawn by the given values."""
    return F.xxhash64(*parts).bitwiseAND(F.lit((1 << 62) - 1))


def coefficients(seed: int, row: int, what: str) -> list[list[int]]:
    """Three random cubic polynomials for one hash function of one sketch row."""
    rng = random.Random(f"{seed}/{row}/{what}")
    return [[rng.randrange(1 if i == 0 else 0, PRIME) for i in range(4)] for _ in range(3)]


def cubic(c: list[int], x: Column) -> Column:
    """Horner's rule; every step uses its input once, so the expression stays linear in size."""
    of = lambda a: a if isinstance(a, Column) else F.lit(a).cast("long")
    out = of(c[0])
    for a in c[1:]:
        out = (out * x + of(a)) % F.lit(PRIME)
    return out


def tab4(c: list[list[int]], fp60: Column) -> Column:
    """4-wise independent hash of a 60-bit value into [0, 2^31 - 1): two characters and their sum, a random cubic of each.

    Of at most four different values one has a character that the others lack.
    """
    low, high = fp60.bitwiseAND(F.lit(LOW30)), F.shiftright(fp60, 30)
    return (cubic(c[0], low) + cubic(c[1], high) + cubic(c[2], (low + high) % F.lit(PRIME))) % F.lit(PRIME)


def tab4_value(c: list[list[int]], fp: int) -> int:
    """The same with Python's integers."""
    low, high = fp & LOW30, fp >> 30
    poly = lambda a, x: (((a[0] * x + a[1]) * x + a[2]) * x + a[3]) % PRIME
    return (poly(c[0], low) + poly(c[1], high) + poly(c[2], (low + high) % PRIME)) % PRIME


def tab4_sql(c: list[list[int]], fp: str) -> str:
    """The same as SQL over BIGINT."""
    def poly(a: list[int], x: str) -> str:
        out = str(a[0])
        for b in a[1:]:
            out = f"(({out}) * {x} + {b}) % {PRIME}"
        return f"({out})"

    low, high = f"({fp} & {LOW30})", f"({fp} >> 30)"
    return f"(({poly(c[0], low)} + {poly(c[1], high)} + {poly(c[2], f'(({low} + {high}) % {PRIME})')}) % {PRIME})"
