"""A small family of bit functions, any four of whose values are almost independent.

A vertex x in GF(2^m) stands for the column (1, x, x^3), of which any four
different ones are linearly independent.  Member j of the family is a vector
over the column's 2m + 1 bits; a vertex's bit is the parity of its column under
that vector.  The vectors come from pairs (g, w) of GF(2^r): bit i is the inner
product of g^i and w, which biases no non-empty test by more than 2m / 2^r.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil, log2

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _irreducible(m: int) -> int:
    """The least irreducible polynomial of degree m over GF(2), as bits."""
    if m == 1:
        return 0b10
    for p in range((1 << m) + 1, 1 << (m + 1), 2):
        if all(_remainder(p, d) for d in range(2, 1 << (m // 2 + 1))):
            return p
    raise AssertionError


def _remainder(a: int, b: int) -> int:
    n = b.bit_length()
    while a.bit_length() >= n:
        a ^= b << (a.bit_length() - n)
    return a


def multiply(a: int, b: int, modulus: int) -> int:
    """Product in GF(2^m), m the degree of the modulus."""
    out = 0
    while b:
        if b & 1:
            out ^= a
        b >>= 1
        a <<= 1
    return _remainder(out, modulus)


#: Irreducible polynomials are searched once a degree; beyond this degree columns no longer fit a long.
MAX_DEGREE = 31
_found: dict[int, int] = {}


def modulus(m: int) -> int:
    if m not in _found:
        # Irreducible trinomials or pentanomials of the degrees at which a search is slow.
        known = {20: (3, 0), 21: (2, 0), 22: (1, 0), 23: (5, 0), 24: (4, 3, 1, 0), 25: (3, 0), 26: (4, 3, 1, 0), 27: (5, 2, 1, 0), 28: (1, 0), 29: (2, 0), 30: (1, 0), 31: (3, 0)}
        _found[m] = (1 << m) | sum(1 << e for e in known[m]) if m in known else _irreducible(m)
    return _found[m]


@dataclass(frozen=True)
class SmallBiasSpace:
    """`bits`: m, so that dense ids lie under 2^m; `alpha`: how far from uniform four bits may be."""

    bits: int
    alpha: float

    def __post_init__(self) -> None:
        if not 1 <= self.bits <= MAX_DEGREE:
            raise ValueError(f"columns of {self.bits} bits do not fit a long")

    @property
    def seed_bits(self) -> int:
        return max(2, ceil(log2(30 * self.bits / self.alpha)))

    @property
    def size(self) -> int:
        return 1 << (2 * self.seed_bits)

    def vector(self, j: int) -> int:
        """The mask of member j; an odd multiplier spreads the degenerate members."""
        r = self.seed_bits
        k = (j * 0x9E3779B1 + 0x7F4A7C15) % self.size
        g, w = k >> r, k & ((1 << r) - 1)
        power, out = 1, 0
        for i in range(2 * self.bits + 1):
            out |= ((power & w).bit_count() & 1) << i
            power = multiply(power, g, modulus(r))
        return out

    def column(self, x: int) -> int:
        """(1, x, x^3) as one number."""
        p = modulus(self.bits)
        cube = multiply(multiply(x, x, p), x, p)
        return 1 | x << 1 | cube << (self.bits + 1)

    def columns(self, x: np.ndarray) -> np.ndarray:
        """`column` of many ids at once."""
        p, m = modulus(self.bits), self.bits

        def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
            out = np.zeros_like(a)
            for i in range(m):
                out ^= np.where(b >> i & 1, a, 0)
                a = a << 1
                a = np.where(a >> m & 1, a ^ p, a)
            return out

        return 1 | x << 1 | times(times(x, x), x) << (m + 1)

    def bit(self, column: Column, j: int) -> Column:
        """Bit of member j for vertices whose `column` value is given."""
        return F.bit_count(column.bitwiseAND(F.lit(self.vector(j)))).cast("int").bitwiseAND(F.lit(1))


def field_columns(ranks: DataFrame, space: SmallBiasSpace, rank: str = "rank", name: str = "column") -> DataFrame:
    """`ranks` with each dense id's column as a long."""
    schema = ranks.schema
    at = ranks.columns.index(rank)

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = pa.array(space.columns(batch.column(at).to_numpy(zero_copy_only=False).astype(np.int64)))
            yield pa.RecordBatch.from_arrays([*batch.columns, values], [*batch.schema.names, name])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema)
    return ranks.mapInArrow(add, f"{fields}, {name} long")
