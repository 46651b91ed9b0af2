"""Triangles at each vertex where members of a group are all linked: twins are counted, not linked.

Members of exactly the same groups are twins: linked with each other and with
the same others.  A class of twins is one weighted vertex of a smaller graph,
whose triangles are counted in cells; those with two or three corners in one
class have a closed form.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import stored, with_position
from .canonical import canonical_edges, orient
from .cells import counted_colours, vertex_counts


def twin_classes(rows: DataFrame, key: list[str], member: str) -> tuple[DataFrame, DataFrame]:
    """Stored (m, twin) of the members that share a group, and (k, twin) of the groups by class; a class is named by its least member."""
    parts = [f"key{i}" for i in range(len(key))]
    held = rows.select(*[F.col(x).alias(p) for x, p in zip(key, parts, strict=True)], F.col(member).cast("long").alias("m")).where(" and ".join(f"{x} is not null" for x in [*parts, "m"])).distinct()
    shared = held.groupBy(*parts).agg(F.count("*").alias("n")).where("n > 1").select(*parts)
    # groups get numbers, so that sets of them are told apart exactly but for a collision of SHA-256
    named = with_position(shared, *parts, name="k")
    grouped = stored(held.join(named, parts).select("k", "m"), "grouped")
    sets = grouped.groupBy("m").agg(F.sha2(F.array_join(F.sort_array(F.collect_list("k")), ","), 256).alias("groups"))
    sets = stored(sets, "sets")
    twins = sets.groupBy("groups").agg(F.min("m").alias("twin"))
    members = stored(sets.join(twins, "groups").select("m", "twin"), "twins")
    return members, grouped.join(twins.select(F.col("twin").alias("m")), "m", "left_semi").select("k", F.col("m").alias("twin"))


def vertex_triangles(rows: DataFrame, key: list[str], member: str, c: int) -> DataFrame:
    """(id, triangles) of every vertex in a triangle of the graph that links members which share a group."""
    members, groups = twin_classes(rows, key, member)
    weights = stored(members.groupBy("twin").agg(F.count("*").alias("w")), "weights")
    groups = stored(groups, "class-groups")
    pairs = groups.toDF("k", "u").join(groups.toDF("k", "v"), "k").where("u < v").select("u", "v")
    o = orient(canonical_edges(pairs))
    o = stored(o.join(weights.toDF("lo", "w_lo"), "lo").join(weights.toDF("hi", "w_hi"), "hi").select("lo", "hi", "w_lo", "w_hi"), "class-edges")
    apart = vertex_counts(o, counted_colours(o.count(), c), weighted=True).toDF("twin", "n")
    # one other corner in the class, or both others in one linked class
    ends = F.array(F.struct(F.col("lo").alias("twin"), F.col("w_hi").alias("w")), F.struct(F.col("hi").alias("twin"), F.col("w_lo").alias("w")))
    near = o.select(F.explode(ends).alias("e")).groupBy("e.twin").agg(F.sum("e.w").alias("linked"), F.sum(F.expr("shiftright(e.w * (e.w - 1), 1)")).alias("both"))
    every = weights.join(near, "twin", "left").join(apart, "twin", "left").na.fill(0, ["linked", "both", "n"])
    others = F.col("w") - 1
    total = F.shiftright(others * (others - 1), 1) + others * F.col("linked") + F.col("both") + F.col("n")
    found = every.select("twin", total.alias("triangles")).where("triangles > 0")
    return members.join(found, "twin").select(F.col("m").alias("id"), "triangles")
