"""Measures of the recursion: subproblem counts, sizes, tails and local hubs."""

from __future__ import annotations

from functools import reduce
from math import copysign, floor, pow

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.colours import refined
from ..operators.recursive import Z, local_hubs
from ..operators.target import PLACES, fits


def _sizes(levels: list[DataFrame]) -> DataFrame:
    parts = [lv.groupBy(*Z).agg(F.count("*").alias("n")).withColumn("level", F.lit(i)) for i, lv in enumerate(levels)]
    return reduce(DataFrame.unionByName, parts)


def rows_per_level(levels: list[DataFrame]) -> DataFrame:
    """(level, n_rows): edges stored over all subproblems of a level."""
    return _sizes(levels).groupBy("level").agg(F.sum("n").alias("n_rows"))


def child_subproblem_sizes(level: DataFrame) -> DataFrame:
    """(z0, z1, z2, n)."""
    return level.groupBy(*Z).agg(F.count("*").alias("n"))


def level_profile(levels: list[DataFrame], edges: int) -> DataFrame:
    """(level, band, subproblems): band s holds sizes from E/4^(s+1) to E/4^s."""
    band = F.floor(F.log(F.lit(float(edges)) / F.col("n")) / F.log(F.lit(4.0)) + 1e-9).cast("long")
    return _sizes(levels).groupBy("level", band.alias("band")).agg(F.count("*").alias("subproblems"))


def tail_share(levels: list[DataFrame], edges: int, k: int = 0) -> DataFrame:
    """(level, subproblems, oversized): sizes of 9E/4^(level - k) or more."""
    over = F.col("n") * F.pow(F.lit(4.0), F.col("level") - k) >= 9.0 * edges
    return _sizes(levels).groupBy("level").agg(F.count("*").alias("subproblems"), F.sum(over.cast("long")).alias("oversized"))


def local_hub_cap(levels: list[DataFrame]) -> DataFrame:
    """(level, most_hubs) over the subproblems of each level."""
    parts = [local_hubs(lv).groupBy(*Z).agg(F.count("*").alias("h")).agg(F.max("h").alias("most_hubs")).withColumn("level", F.lit(i)) for i, lv in enumerate(levels)]
    return reduce(DataFrame.unionByName, parts).select("level", F.coalesce("most_hubs", F.lit(0)).alias("most_hubs"))


def role_class_sizes(level: DataFrame) -> DataFrame:
    """(z0, z1, z2, tip_mid, tip_top, base): how many edges each role has."""
    names = ("tip_mid", "tip_top", "base")
    return level.groupBy(*Z).agg(*[F.sum(fits("x_lo", "x_hi", p).cast("long")).alias(n) for n, p in zip(names, PLACES, strict=True)])


def _rounded(x: float, places: int) -> float:
    """As the SQL's round: the product with the power of ten, halves away from zero."""
    scaled = abs(x) * 10.0**places
    whole = floor(scaled)
    return copysign((whole + (scaled - whole >= 0.5)) / 10.0**places, x)


def role_class_moments(roles: list[DataFrame], edges: int) -> list[tuple[int, float, float, float]]:
    """(level, mean_size, expected, variance) of the role classes of each level, from the tables of `role_class_sizes`.

    The sums are exact.  The difference of squares that follows loses digits
    once E * E passes 2^53, so it is made of the operations of the SQL, the C
    library's `pow` among them: that of the JVM rounds otherwise.
    """
    names = ("tip_mid", "tip_top", "base")
    total = F.sum(F.col("tip_mid") + F.col("tip_top") + F.col("base")).cast("decimal(38,0)")
    square = F.sum(sum((F.col(x).cast("decimal(19,0)") * F.col(x) for x in names), F.lit(0).cast("decimal(38,0)")))
    sums = [r.agg(F.lit(i).alias("level"), total.alias("total"), square.cast("decimal(38,0)").alias("square")) for i, r in enumerate(roles)]
    out = []
    for x in reduce(DataFrame.unionByName, sums).where("total is not null").collect():  # one row a level
        cells = 3.0 * 8**x.level
        mean = float(int(x.total)) / cells
        variance = float(int(x.square)) / cells - pow(mean, 2.0)
        out.append((x.level, _rounded(mean, 6), _rounded(edges / 4.0**x.level, 6), _rounded(variance, 2)))
    return out


def role_moments_over_seeds(edges: DataFrame, levels: int, seeds: tuple[int, ...]) -> DataFrame:
    """(level, seeds, mean_size, expected, variance, bound) of one role class, over the seeds of the colouring.

    The class is that of the first colour at both ends; by symmetry every other
    one has the same moments.  All seeds are counted in one pass.
    """
    held = lambda i, s: F.sum(((refined(F.col("lo"), i, s) == 1) & (refined(F.col("hi"), i, s) == 1)).cast("long"))
    named = [(i, s) for i in range(1, levels + 1) for s in seeds]
    counts = edges.agg(F.count("*").alias("e"), *[F.coalesce(held(i, s), F.lit(0)).alias(f"n_{i}_{s}") for i, s in named])
    rows = counts.select("e", F.inline(F.array(*[F.struct(F.lit(i).alias("level"), F.col(f"n_{i}_{s}").cast("double").alias("x")) for i, s in named])))
    e, mean = F.max("e").cast("double"), F.sum("x") / F.count("*")
    return rows.groupBy("level").agg(
        F.count("*").alias("seeds"),
        F.round(mean, 6).alias("mean_size"),
        F.round(e / F.pow(F.lit(4.0), F.col("level")), 6).alias("expected"),
        F.round(F.sum(F.col("x") * F.col("x")) / F.count("*") - F.pow(mean, F.lit(2)), 2).alias("variance"),
        F.round(3 * e * e / F.pow(F.lit(16.0), F.col("level")), 2).alias("bound"),
    )
