"""Affine hash families modulo a prime, as Column expressions.

One family serves all tiles, so a cell has the same hash wherever it occurs and lists can be merged.  Hashes are integer
numerators in [0, P); the unit interval appears only in estimates.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2**31 - 1  # a*id + b stays below 2^62 + 2^31
LARGE = 2**61 - 1  # for ids from PRIME on; products are taken by halves of 31 bits


def prime_for(largest: int) -> int:
    """The modulus for ids up to ``largest``: ids must lie below it, else two of them share every hash."""
    if largest >= LARGE:
        raise ValueError("ids must be below 2^61 - 1")
    return PRIME if largest < PRIME else LARGE


def draw(*key) -> int:
    """52 random bits from a key; SQL gets the same from the first 13 digits of md5."""
    return int(hashlib.md5("|".join(map(str, key)).encode()).hexdigest()[:13], 16)


@dataclass(frozen=True)
class Family:
    """``reps`` pairs of affine maps (a_row, b_row, a_col, b_col)."""

    maps: tuple[tuple[int, int, int, int], ...]
    prime: int = PRIME

    @property
    def reps(self) -> int:
        return len(self.maps)


def family(reps: int = 10, seed: int = 42, prime: int = PRIME) -> Family:
    one = lambda r, name, low: low + draw(seed, r, name) % (prime - low)
    return Family(tuple((one(r, "ar", 1), one(r, "br", 0), one(r, "ac", 1), one(r, "bc", 0)) for r in range(reps)), prime)


def affine(x: Column, a: int | Column, b: int | Column, prime: int = PRIME) -> Column:
    a, b = (F.lit(v).cast("long") if isinstance(v, int) else v for v in (a, b))
    p = F.lit(prime).cast("long")
    x = F.pmod(x, p)
    if prime <= PRIME:
        return (a * x + b) % p
    if prime != LARGE:
        raise ValueError("the modulus is at most 2^31 - 1, or 2^61 - 1")
    low = F.lit(2**31 - 1).cast("long")
    a1, a0, x1, x0 = F.shiftright(a, 31), a.bitwiseAND(low), F.shiftright(x, 31), x.bitwiseAND(low)
    middle = (a1 * x0 + a0 * x1) % p  # below 2^62 before the remainder; times 2^31 is a turn of the 61 bits
    turned = F.shiftleft(middle.bitwiseAND(F.lit(2**30 - 1).cast("long")), 31) + F.shiftright(middle, 30)
    return (((2 * (a1 * x1)) % p + turned) % p + ((a0 * x0) % p + b) % p) % p


def np_affine(x: np.ndarray, a: int, b: int, prime: int = PRIME) -> np.ndarray:
    """The same over an array."""
    if prime <= PRIME:
        return (a * (x % prime) + b) % prime
    return np.array([(a * v + b) % prime for v in x.tolist()], np.int64)


def cell(h_row: Column, h_col: Column, prime: int = PRIME) -> Column:
    """Row hash minus column hash, wrapped into [0, P)."""
    return (h_row - h_col + F.lit(prime).cast("long")) % F.lit(prime).cast("long")


def maps_column(fam: Family) -> Column:
    """The family as an array literal of structs, to be exploded."""
    return F.array(*(F.struct(F.lit(i).alias("rep"), *(F.lit(v).cast("long").alias(n) for v, n in zip(m, ("ar", "br", "ac", "bc"), strict=True))) for i, m in enumerate(fam.maps)))


def uniform(*keys: Column | str | int) -> Column:
    """A reproducible uniform from the keys, the same in SQL: 13 hex digits of md5 over 2^52."""
    parts = [F.lit(str(k)) if isinstance(k, int) else (F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("double") / float(2**52)
