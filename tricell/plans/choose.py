"""A planner that picks the method of least cost in rows moved."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MemoryModel
from ..operators.baselines import base_scan_triangles, naive_triangles, sort_wedge_triangles
from ..operators.cells import enumerate_cells


def statistics(ranked: DataFrame) -> tuple[int, int]:
    """(edges, paths a - b - c in rank order), by one aggregation over the vertices."""
    ends = F.explode(F.array(F.struct(F.col("lo").alias("v"), F.lit(1).alias("leaves")), F.struct(F.col("hi").alias("v"), F.lit(0).alias("leaves")))).alias("end")
    vertices = ranked.select(ends).groupBy("end.v").agg(F.sum("end.leaves").alias("leave"), F.sum(1 - F.col("end.leaves")).alias("enter"))
    paths = F.sum((F.col("leave").cast("decimal(19,0)") * F.col("enter")).cast("decimal(38,0)"))
    row = vertices.agg(F.sum("leave").alias("e"), paths.alias("w")).first()
    return int(row.e or 0), int(row.w or 0)


#: what a row costs that a task joins without moving it, in rows moved
JOINED = 0.3


def volumes(edges: int, paths: int, mm: MemoryModel, alpha: float = 0.5) -> dict[str, int]:
    """What each method costs, in rows moved.

    Every method meets the paths and closes them.  The plain join and the
    sort-based method move them; batches and cells join them where they are
    made, and move copies of the edges instead.
    """
    c = mm.colours(edges)
    batches = -(-edges // max(1, int(alpha * mm.m)))
    depth = max(0, (c - 1).bit_length())
    inside = int(JOINED * paths)
    return {
        "plain": 3 * edges + paths,
        "sort_wedge": 3 * edges + paths + inside,
        "base_scan": batches * edges + inside,
        "cells": 3 * c * edges + inside,
        "steered": 3 * c * edges + 2 * 64 * depth * edges + inside,
        "recursive": sum((3 * 2**i - 2) * edges for i in range(depth + 1)) + inside,
    }


def choose(ranked: DataFrame, mm: MemoryModel) -> str:
    v = volumes(*statistics(ranked), mm)
    return min(v, key=lambda k: (v[k], k))


def enumerate_planned(ranked: DataFrame, mm: MemoryModel) -> DataFrame:
    """Triangles by the method that the planner picks."""
    method = choose(ranked, mm)
    if method == "plain":
        return naive_triangles(ranked.select("lo", "hi"))
    if method == "sort_wedge":
        return sort_wedge_triangles(ranked.select("lo", "hi"))
    if method == "base_scan":
        return base_scan_triangles(ranked.select("lo", "hi"), mm)
    return enumerate_cells(ranked, mm)


def sampled_estimate(ranked: DataFrame, p: float, seed: int = 1) -> float:
    """Triangles of a sample of the edges at rate p, scaled by p^3: a statistic for planning, not a result."""
    kept = ranked.where(F.pmod(F.xxhash64(F.lit(seed), "lo", "hi"), F.lit(1_000_000)) < int(p * 1_000_000))
    return sort_wedge_triangles(kept.select("lo", "hi")).count() / p**3
