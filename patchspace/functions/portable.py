"""Integer arithmetic that Spark and other SQL engines evaluate alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed values of the portable hash: multiplier, increment, shifts of its three rounds.
MULTIPLIER, INCREMENT, SHIFTS, MODULUS = 1103515245, 12345, (15, 13, 16), 1 << 31


def _step(x: Column) -> Column:
    return F.pmod(F.pmod(x, F.lit(MODULUS)) * MULTIPLIER + INCREMENT, F.lit(MODULUS))


def portable_hash(x: Column) -> Column:
    """A hash below 2^31 of a non-negative integer; reduces first, so nothing overflows."""
    x = x.cast("long")
    for s in SHIFTS:
        x = _step(x)
        x = x.bitwiseXOR(F.shiftright(x, s))
    return x


def portable_hash_sql(x: str) -> str:
    for s in SHIFTS:
        x = f"(((({x}) % {MODULUS}) * {MULTIPLIER} + {INCREMENT}) % {MODULUS})"
        x = f"xor({x}, {x} >> {s})"
    return x


def cents(x: Column) -> Column:
    """An amount as an integer, so that sums do not depend on row order."""
    return F.round(x * 100).cast("long")
