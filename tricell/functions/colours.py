"""Vertex colours as column expressions; no table of colours is ever kept."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2**31 - 1
WIDE_PRIME = 2**61 - 1


def coefficients(seed: int, degree: int = 3, prime: int = PRIME, level: int | str | None = None) -> list[int]:
    """Leading coefficient first; uniform over the whole field, zero included, as independence asks."""
    draw = random.Random(seed if level is None else f"{seed}/{level}")
    return [draw.randrange(prime) for _ in range(degree + 1)]


def polynomial(x: Column, ks: list[int]) -> Column:
    """Value modulo 2^31 - 1 of ids that are taken into the field."""
    inside = F.pmod(x, F.lit(PRIME))
    h = F.lit(ks[0]).cast("long")
    for k in ks[1:]:
        h = F.pmod(h * inside + F.lit(k), F.lit(PRIME))
    return h


def wide_polynomial(x: Column, ks: list[int]) -> Column:
    """Value modulo 2^61 - 1 of ids that are taken into the field, in exact decimals."""
    p = F.lit(WIDE_PRIME).cast("decimal(19,0)")
    d = F.pmod(x, F.lit(WIDE_PRIME)).cast("decimal(19,0)")
    h = F.lit(ks[0]).cast("decimal(19,0)")
    for k in ks[1:]:
        product = (h * d).cast("decimal(38,0)") % p
        h = ((product + F.lit(k).cast("decimal(19,0)")) % p).cast("decimal(19,0)")
    return h.cast("long")


def independent(x: Column, seed: int, degree: int = 3, level: int | None = None) -> Column:
    """A random polynomial of the id, over the small field for ids inside it and over the wide one for all others.

    The two polynomials are drawn independently, so any four ids of 0..2^61 - 2
    get independent values, whichever side each lies on.  Ids outside that range
    get a value too, shared by those that are equal modulo 2^61 - 1.
    """
    small = polynomial(x, coefficients(seed, degree, level=level))
    wide = wide_polynomial(x, coefficients(seed, degree, WIDE_PRIME, f"wide/{level}"))
    return F.when((x >= 0) & (x < PRIME), small).otherwise(wide)


def colour(x: Column, c: int, seed: int, family: str = "poly4") -> Column:
    """A colour from 1 to c, for any id.  `poly4` is four-wise independent; the others serve comparisons."""
    if c == 1 or family == "constant":
        return F.lit(1).cast("int")
    if family == "poly4":
        h = independent(x, seed)
    elif family == "poly2":
        h = independent(x, seed, 1)
    elif family == "wide":
        h = wide_polynomial(x, coefficients(seed, prime=WIDE_PRIME))
    elif family == "xxhash":
        h = F.pmod(F.xxhash64(F.lit(seed), x), F.lit(PRIME))
    elif family == "modulo":
        h = x
    else:
        raise ValueError(f"no colour family {family!r}")
    return (F.pmod(h, F.lit(c)) + 1).cast("int")


def bit(x: Column, level: int, seed: int) -> Column:
    """One random bit a vertex, of a four-wise independent function for each level."""
    return F.pmod(independent(x, seed, level=level), F.lit(2)).cast("int")


def bit_array(x: np.ndarray, level: int, seed: int) -> np.ndarray:
    """The same bits of ids held in memory."""

    def value(v: np.ndarray, prime: int, label: int | str) -> np.ndarray:
        ks = coefficients(seed, prime=prime, level=label)
        h = ks[0]
        for k in ks[1:]:
            h = (h * v + k) % prime
        return (h % 2).astype(np.int64)

    small = (x >= 0) & (x < PRIME)
    out = np.zeros(len(x), np.int64)
    out[small] = value(x[small].astype(np.int64), PRIME, level)
    if not small.all():
        # products of the wide field need whole numbers of any size
        out[~small] = value(x[~small].astype(object) % WIDE_PRIME, WIDE_PRIME, f"wide/{level}")
    return out


def refined(x: Column, level: int, seed: int) -> Column:
    """The colour of a vertex after `level` refinements, in 1..2^level: each turns z into 2z or 2z - 1."""
    z = F.lit(1)
    for i in range(1, level + 1):
        z = 2 * z - bit(x, i, seed)
    return z.cast("int")


def role_cell(role: str, low: Column, high: Column, free: Column, c: int) -> Column:
    """The cell that an edge serves in one role for a value 0..c-1 of the free colour."""
    a, b = (low - 1).cast("long"), (high - 1).cast("long")
    if role == "tip_mid":
        return (a * c + b) * c + free
    if role == "tip_top":
        return (a * c + free) * c + b
    if role == "base":
        return (free * c + a) * c + b
    raise ValueError(f"no role {role!r}")
