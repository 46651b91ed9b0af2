"""Triangles at given vertices: of one vertex, of a set, and by subproblem.

Edges come ranked: (lo, hi, deg_lo, deg_hi), as `orient(..., keep_degrees=True)` gives them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def in_rank_order(h: Column, lo: Column, hi: Column) -> list[Column]:
    """Columns a, b, c of the triangle of `h` and the oriented edge; all are structs (deg, id)."""
    a = F.when(h < lo, h).otherwise(lo)
    c = F.when(h > hi, h).otherwise(hi)
    b = F.when(h < lo, lo).when(h > hi, hi).otherwise(h)
    return [a["id"].alias("a"), b["id"].alias("b"), c["id"].alias("c")]


def _point(prefix: str) -> Column:
    return F.struct(F.col(f"deg_{prefix}").alias("deg"), F.col(prefix).alias("id"))


def triangles_at(ranked: DataFrame, v: int) -> DataFrame:
    """All triangles with vertex `v`: edges with both ends among its neighbours."""
    touching = ranked.where((F.col("lo") == v) | (F.col("hi") == v))
    near = touching.select(F.when(F.col("lo") == v, F.col("hi")).otherwise(F.col("lo")).alias("x"), F.when(F.col("lo") == v, F.col("deg_lo")).otherwise(F.col("deg_hi")).alias("dv"))
    own = near.agg(F.max("dv").alias("deg_v"))
    inside = ranked.join(near.select(F.col("x").alias("lo")), "lo", "left_semi").join(near.select(F.col("x").alias("hi")), "hi", "left_semi")
    h = F.struct(F.col("deg_v").alias("deg"), F.lit(v).cast("long").alias("id"))
    # one row on the right: the degree of v
    return inside.join(F.broadcast(own)).select(*in_rank_order(h, _point("lo"), _point("hi")))


def hub_neighbours(edges: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, h, deg_h, x) for each end of an edge that is a hub; edges carry hub_lo and hub_hi."""
    ends = F.array(
        F.when(F.col("hub_lo"), F.struct(F.col("lo").alias("h"), F.col("deg_lo").alias("deg_h"), F.col("hi").alias("x"))),
        F.when(F.col("hub_hi"), F.struct(F.col("hi").alias("h"), F.col("deg_hi").alias("deg_h"), F.col("lo").alias("x"))),
    )
    touching = edges.where("hub_lo or hub_hi").select(*keys, F.explode(F.array_compact(ends)).alias("e"))
    return touching.select(*keys, "e.h", "e.deg_h", "e.x")


def triangles_at_set(marked: DataFrame, keys: list[str] | None = None, exactly_once: bool = True, extra: list[str] | None = None, fits: Column | None = None) -> DataFrame:
    """Triangles with a hub; `marked` edges say in hub_lo and hub_hi which ends are hubs.

    A triangle of several hubs is credited to the highest-ranked one, so it
    appears once; without `exactly_once` it appears once for each of its hubs.
    With `keys`, each value of the keys is a graph of its own.  `fits` tells which
    edges and hubs may make a triangle, before it is closed: over the edges'
    columns and over the points `hub_point`, `lo_point` and `hi_point` (deg, id).
    """
    keys, extra = keys or [], extra or []
    near = hub_neighbours(marked, keys)
    h, lo, hi = _point("h"), _point("lo"), _point("hi")
    if exactly_once:
        # only a neighbour below the hub, or no hub itself, leaves the credit here
        first = marked.select("*", F.when(F.col("hub_lo"), lo).alias("low_hub"), F.when(F.col("hub_hi"), hi).alias("high_hub"))
    else:
        first = marked.select("*", F.lit(None).cast("struct<deg:bigint,id:bigint>").alias("low_hub"), F.lit(None).cast("struct<deg:bigint,id:bigint>").alias("high_hub"))
    at_low = near.withColumnRenamed("x", "lo")
    joined = first.join(at_low, [*keys, "lo"]).where("h <> hi")
    joined = joined.where(F.coalesce(F.col("low_hub") < h, F.lit(True)) & F.coalesce(F.col("high_hub") < h, F.lit(True)))
    if fits is not None:
        joined = joined.withColumns({"hub_point": h, "lo_point": lo, "hi_point": hi}).where(fits).drop("hub_point", "lo_point", "hi_point")
    closed = joined.join(near.select(*keys, "h", F.col("x").alias("hi")), [*keys, "h", "hi"])
    return closed.select(*keys, *extra, *in_rank_order(h, lo, hi))
