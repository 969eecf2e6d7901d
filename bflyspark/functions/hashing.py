"""Keep-or-drop by modular arithmetic, so that any engine draws the same sample."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# A prime modulus and multipliers below 2^16, so that products of ids below 2^40 don't overflow.
PRIME = 1_000_003
FACTORS = (48271, 16807, 40692, 39373)


def portable_hash(columns: list[Column], seed: int) -> Column:
    """In [0, PRIME): the columns, reduced, times fixed factors, twice scrambled by a quadratic step."""
    total = F.lit(seed % PRIME).cast("long")
    for c, f in zip(columns, FACTORS, strict=False):
        total = F.pmod((total + F.pmod(c, F.lit(PRIME)) + 1) * f, F.lit(PRIME))
    return F.pmod(total * total + total * 7919, F.lit(PRIME))


def kept(columns: list[Column], share: float, seed: int) -> Column:
    """Bernoulli choice with probability share."""
    return portable_hash(columns, seed) < F.lit(round(share * PRIME))


def hash_sql(columns: list[str], seed: int) -> str:
    """The same hash as SQL text."""
    total = str(seed % PRIME)
    for c, f in zip(columns, FACTORS, strict=False):
        total = f"((({total} + ((({c}) % {PRIME}) + {PRIME}) % {PRIME} + 1) * {f}) % {PRIME})"
    return f"((({total}) * ({total}) + ({total}) * 7919) % {PRIME})"


def kept_sql(columns: list[str], share: float, seed: int) -> str:
    """The same choice as SQL text."""
    return f"{hash_sql(columns, seed)} < {round(share * PRIME)}"
