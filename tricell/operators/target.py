"""Targeted enumeration: the triangles whose ordered colours are a given triple, keyed by subproblem."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PLACES = (("z0", "z1"), ("z0", "z2"), ("z1", "z2"))


def fits(low: str, high: str, places: tuple[str, str]) -> Column:
    """Whether an edge's colours are those that the triple asks for at two places."""
    return (F.col(low) == F.col(places[0])) & (F.col(high) == F.col(places[1]))


def compatible(low: str = "x_lo", high: str = "x_hi") -> Column:
    """Whether an edge can be part of a triangle of the triple (z0, z1, z2)."""
    return fits(low, high, PLACES[0]) | fits(low, high, PLACES[1]) | fits(low, high, PLACES[2])


def keyed_triangles(level: DataFrame, merge: bool = True) -> DataFrame:
    """(z0, z1, z2, a, b, c) of each subproblem: sort, scan and merge only, if `merge`."""
    z = ["z0", "z1", "z2"]
    roles = [level.where(fits("x_lo", "x_hi", p)) for p in PLACES]
    mid = roles[0].select(*z, F.col("lo").alias("a"), F.col("hi").alias("b"))
    top = roles[1].select(*z, F.col("lo").alias("a"), F.col("hi").alias("c"))
    base = roles[2].select(*z, F.col("lo").alias("b"), F.col("hi").alias("c"))
    if merge:
        top, base = top.hint("merge"), base.hint("merge")
    return mid.join(base, [*z, "b"]).join(top, [*z, "a", "c"]).select(*z, "a", "b", "c")


def enumerate_target(painted: DataFrame, triple: tuple[int, int, int]) -> DataFrame:
    """Triangles of edges (lo, hi, x_lo, x_hi) whose vertices in rank order have the colours `triple`."""
    named = painted
    for name, value in zip(("z0", "z1", "z2"), triple, strict=True):
        named = named.withColumn(name, F.lit(value))
    return keyed_triangles(named.where(compatible()), merge=False).select("a", "b", "c")
