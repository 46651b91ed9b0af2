"""Simple graphs in rank order: vertices by degree, ties by id."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import require_columns
from ..tables import with_position


def canonical_edges(pairs: DataFrame, src: str = "u", dst: str = "v") -> DataFrame:
    """Each edge once as (u, v), u < v; loops, repeats, reversals and null ends go."""
    require_columns(pairs, src, dst)
    u, v = F.col(src).cast("long"), F.col(dst).cast("long")
    return pairs.select(F.least(u, v).alias("u"), F.greatest(u, v).alias("v"), (u != v).alias("_ok")).where("_ok").select("u", "v").distinct()


def degrees(edges: DataFrame) -> DataFrame:
    """(id, deg) of every vertex with an edge."""
    a, b = edges.columns[:2]
    ends = edges.select(F.explode(F.array(a, b)).alias("id"))
    return ends.groupBy("id").agg(F.count("*").alias("deg"))


def orient(edges: DataFrame, keep_degrees: bool = False, keep: Sequence[str] = (), deg: DataFrame | None = None) -> DataFrame:
    """(lo, hi): each edge from its lower to its higher end in rank order, with the columns `keep` of its own.

    Degrees that are stored already tell the planner their size, so that few of them are sent to the edges.
    """
    require_columns(edges, "u", "v")
    deg = degrees(edges) if deg is None else deg
    both = edges.join(deg.toDF("u", "du"), "u").join(deg.toDF("v", "dv"), "v")
    a, b = F.struct("du", "u"), F.struct("dv", "v")
    up = a < b
    out = both.select(
        F.when(up, F.col("u")).otherwise(F.col("v")).alias("lo"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("hi"),
        F.least("du", "dv").alias("deg_lo"), F.greatest("du", "dv").alias("deg_hi"), *keep,
    )
    return out if keep_degrees else out.select("lo", "hi", *keep)


def dense_rank_ids(deg: DataFrame) -> DataFrame:
    """(id, rank): 0-based position in rank order, without a one-partition window."""
    return with_position(deg.select("deg", "id"), "deg", "id", name="rank").select("id", "rank")


def successor_lists(oriented: DataFrame) -> DataFrame:
    """(lo, succ): the higher neighbours of each vertex, sorted by id."""
    return oriented.groupBy("lo").agg(F.sort_array(F.collect_list("hi")).alias("succ"))


def vertex_dictionary(names: DataFrame, name: str = "name") -> DataFrame:
    """(id, name): ids by sorted name, so that any engine can build them again."""
    return with_position(names.select(name).distinct(), name, name="id").select("id", name)
