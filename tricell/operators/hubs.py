"""Vertices of very high degree, and the edges that touch them."""

from __future__ import annotations

from math import isqrt

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def least_hub_degree(edges: int, m: int) -> int:
    """The least integer degree whose square exceeds E * M."""
    return isqrt(edges * m) + 1


def mark_hubs(ranked: DataFrame, least: int) -> DataFrame:
    """Ranked edges with hub_lo and hub_hi; no join is needed as edges know their ends' degrees."""
    return ranked.withColumn("hub_lo", F.col("deg_lo") >= least).withColumn("hub_hi", F.col("deg_hi") >= least)


def hub_vertices(deg: DataFrame, least: int) -> DataFrame:
    return deg.where(F.col("deg") >= least)


def touches_hub() -> Column:
    return F.col("hub_lo") | F.col("hub_hi")


def split_hubs(ranked: DataFrame, edges: int, m: int, threshold: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(hubs, edges at hubs, the other edges); `threshold` overrides the least hub degree."""
    marked = mark_hubs(ranked, threshold or least_hub_degree(edges, m))
    ends = F.array(F.struct(F.col("lo").alias("id"), F.col("deg_lo").alias("deg")), F.struct(F.col("hi").alias("id"), F.col("deg_hi").alias("deg")))
    hubs = marked.where(touches_hub()).select(F.explode(ends).alias("e")).select("e.*").distinct()
    return hubs.where(F.col("deg") >= (threshold or least_hub_degree(edges, m))), marked.where(touches_hub()), marked.where(~touches_hub())
