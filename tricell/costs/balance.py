"""How evenly a colouring spreads edges: class and cell sizes, pair mass and its bounds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.cells import routed_once

def pairs(n: str) -> Column:
    """n(n - 1)/2 in whole numbers."""
    return F.shiftright(F.col(n) * (F.col(n) - 1), 1)


def class_sizes(classed: DataFrame) -> DataFrame:
    """(k_lo, k_hi, n)."""
    return classed.groupBy("k_lo", "k_hi").agg(F.count("*").alias("n"))


def cell_sizes(classed: DataFrame, c: int) -> DataFrame:
    """(cell, n): edges that each cell holds, roles merged."""
    return routed_once(classed, c).groupBy("cell").agg(F.count("*").alias("n"))


def peak_cell(classed: DataFrame, c: int) -> DataFrame:
    return cell_sizes(classed, c).agg(F.max("n").alias("peak_edges"))


def pair_mass(classed: DataFrame) -> DataFrame:
    """One row: unordered pairs of edges that share a class."""
    return class_sizes(classed).agg(F.sum(pairs("n")).alias("pair_mass"))


def pair_mass_split(classed: DataFrame) -> DataFrame:
    """One row: the pair mass, the pairs of it that share a vertex, and those that do not."""
    ends = classed.select("k_lo", "k_hi", F.explode(F.array("lo", "hi")).alias("v")).groupBy("k_lo", "k_hi", "v").agg(F.count("*").alias("d"))
    both = pair_mass(classed).crossJoin(ends.agg(F.sum(pairs("d")).alias("adjacent")))
    return both.select("pair_mass", "adjacent", (F.col("pair_mass") - F.col("adjacent")).alias("apart"))


def pair_mass_bound(low_degrees: DataFrame, edges: int, c: int, m: int) -> DataFrame:
    """One row: the expected pair mass under four-wise independence, and E * M."""
    adjacent = low_degrees.agg(F.coalesce(F.sum(pairs("deg")), F.lit(0)).alias("p"))
    expected = F.lit(edges * (edges - 1) // 2) / F.lit(float(c * c)) + F.col("p") / F.lit(float(c))
    return adjacent.select(F.round(expected, 6).alias("expected_bound"), F.lit(edges * m).cast("long").alias("edges_times_memory"))


def hub_report(deg: DataFrame, least: int, c: int) -> DataFrame:
    """One row: hubs, the edge ends at hubs, and the most hubs that degrees allow."""
    hubs = deg.where(F.col("deg") >= least)
    return hubs.agg(F.count("*").alias("hubs"), F.coalesce(F.sum("deg"), F.lit(0)).alias("hub_ends")).withColumn("hub_limit", F.lit(2 * c).cast("long"))
