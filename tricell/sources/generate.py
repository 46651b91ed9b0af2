"""Graphs with known numbers of triangles, from ranges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def clique(spark: SparkSession, n: int) -> DataFrame:
    """Complete graph: n(n-1)(n-2)/6 triangles, for n of two or more."""
    u = spark.range(max(n - 1, 0)).toDF("u")
    return u.select("u", F.explode(F.sequence(F.col("u") + 1, F.lit(max(n - 1, 1)).cast("long"))).alias("v"))


def wheel(spark: SparkSession, n: int) -> DataFrame:
    """Hub 0 and a rim of n vertices: n triangles."""
    rim = spark.range(1, n + 1).toDF("v")
    spokes = rim.select(F.lit(0).cast("long").alias("u"), "v")
    return spokes.unionByName(rim.select(F.col("v").alias("u"), (F.col("v") % n + 1).alias("v")))


def tripartite(spark: SparkSession, p: int, q: int, r: int) -> DataFrame:
    """Complete tripartite graph: p * q * r triangles."""
    def sides(n: int, m: int, low: int, high: int) -> DataFrame:
        return spark.range(n).select((F.col("id") + low).alias("u"), F.explode(F.sequence(F.lit(high).cast("long"), F.lit(high + m - 1).cast("long"))).alias("v"))

    return sides(p, q, 0, p).unionByName(sides(q, r, p, p + q)).unionByName(sides(p, r, 0, p + q))


def book(spark: SparkSession, n: int) -> DataFrame:
    """n triangles on the edge (0, 1)."""
    leaves = spark.range(2, n + 2).toDF("v")
    spine = spark.range(1).select(F.lit(0).cast("long").alias("u"), F.lit(1).cast("long").alias("v"))
    return spine.unionByName(leaves.select(F.lit(0).cast("long").alias("u"), "v")).unionByName(leaves.select(F.lit(1).cast("long").alias("u"), "v"))


def three_hubs(spark: SparkSession, n: int) -> DataFrame:
    """Three hubs joined to each other and to n leaves: 1 + 3n triangles."""
    leaves = spark.range(3, n + 3).select(F.explode(F.sequence(F.lit(0), F.lit(2)).cast("array<long>")).alias("u"), F.col("id").alias("v"))
    return clique(spark, 3).unionByName(leaves)


def star(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(1, n + 1).select(F.lit(0).cast("long").alias("u"), F.col("id").alias("v"))


def random_pairs(spark: SparkSession, vertices: int, pairs: int, seed: int = 1) -> DataFrame:
    """Pairs by hash, the same on every run; may hold loops and repeats."""
    at = lambda salt: F.pmod(F.xxhash64(F.lit(seed), F.lit(salt), "id"), F.lit(vertices))
    return spark.range(pairs).select(at(0).alias("u"), at(1).alias("v"))
