"""What users do with triangles: emit, count, clustering, support, a truss round."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F


def emit(tri: DataFrame, call: Callable[[int, int, int], None]) -> None:
    """Call once a triangle, on the executors.  A task that runs again calls again, so `call` must be idempotent by (a, b, c)."""

    def each(rows: Iterable[Row]) -> None:
        for r in rows:
            call(r.a, r.b, r.c)

    tri.foreachPartition(each)


def count_triangles(tri: DataFrame) -> int:
    return tri.count()


def exactly_once(tri: DataFrame) -> DataFrame:
    """One row: rows, distinct rows."""
    per = tri.groupBy("a", "b", "c").agg(F.count("*").alias("n"))
    return per.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"), F.count("*").alias("n_distinct"))


def vertex_triangles(tri: DataFrame) -> DataFrame:
    """(id, triangles)."""
    return tri.select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count("*").alias("triangles"))


def clustering(tri: DataFrame, deg: DataFrame) -> DataFrame:
    """(id, deg, triangles, local_clustering): of a vertex's neighbour pairs, the share that is joined."""
    t = deg.join(vertex_triangles(tri), "id", "left").select("id", "deg", F.coalesce("triangles", F.lit(0)).alias("triangles"))
    pairs = F.col("deg") * (F.col("deg") - 1)
    share = F.when(pairs > 0, 2 * F.col("triangles") / pairs).otherwise(F.lit(0.0))
    return t.withColumn("local_clustering", F.round(share, 6))


def transitivity(tri: DataFrame, deg: DataFrame) -> DataFrame:
    """One row: triangles, wedges and 3 * triangles / wedges."""
    wedges = deg.agg(F.sum(F.shiftright(F.col("deg") * (F.col("deg") - 1), 1)).alias("wedges"))
    both = tri.agg(F.count("*").alias("triangles")).crossJoin(wedges)
    return both.select("triangles", "wedges", F.round(3 * F.col("triangles") / F.col("wedges"), 6).alias("transitivity"))


def edge_support(tri: DataFrame, edges: DataFrame) -> DataFrame:
    """(lo, hi, support): how many triangles each edge is in."""
    sides = F.array(*[F.struct(F.col(x).alias("lo"), F.col(y).alias("hi")) for x, y in (("a", "b"), ("a", "c"), ("b", "c"))])
    held = tri.select(F.explode(sides).alias("e")).groupBy("e").agg(F.count("*").alias("support")).select("e.lo", "e.hi", "support")
    return edges.select("lo", "hi").join(held, ["lo", "hi"], "left").select("lo", "hi", F.coalesce("support", F.lit(0)).alias("support"))


def truss_round(tri: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """Edges in at least k - 2 triangles: one round towards the k-truss."""
    return edge_support(tri, edges).where(F.col("support") >= k - 2).select("lo", "hi")
