"""Deterministic enumeration: a colouring built bit by bit, each bit steered by a potential.

At every level all candidate bits of a chunk are scored in one pass over the
edges.  A candidate splits a class in four; three sums of bits over the class
give the four sizes, and two over a vertex's edges in it give what the vertex
has in each, so no edge is copied for a candidate.  The least potential is taken, ties by least number;
no chance is involved, so two runs agree to the row.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction
from math import log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.small_bias import SmallBiasSpace, field_columns
from ..model import MemoryModel
from ..tables import stored
from .canonical import dense_rank_ids
from .cells import join_kernel
from .cone import triangles_at_set
from .hubs import least_hub_degree, mark_hubs, touches_hub


@dataclass
class SteeredColouring:
    """The members chosen, and the scaled potential and its cap at every level."""

    space: SmallBiasSpace
    colours: int
    members: list[int] = field(default_factory=list)
    potentials: list[int] = field(default_factory=list)
    caps: list[Fraction] = field(default_factory=list)
    adjacent: list[int] = field(default_factory=list)
    apart: list[int] = field(default_factory=list)

    def colour(self, column: Column) -> Column:
        x = F.lit(1)
        for j in self.members:
            x = 2 * x - self.space.bit(column, j)
        return x.cast("int")


def default_alpha(c: int) -> float:
    """1 / log c, which keeps the final pair mass under e times E * M."""
    return 1.0 / max(1.0, log2(c))


def with_columns(low: DataFrame, degrees: DataFrame, alpha: float) -> tuple[DataFrame, SmallBiasSpace]:
    """Edges with their ends' field columns y_lo and y_hi; the space is sized to the vertices."""
    ranks = dense_rank_ids(degrees)
    n = degrees.count()
    space = SmallBiasSpace(max(2, (max(n - 1, 1)).bit_length()), alpha)
    columns = stored(field_columns(ranks, space), "columns").select("id", "column")
    edges = low.select("lo", "hi").join(columns.toDF("lo", "y_lo"), "lo").join(columns.toDF("hi", "y_hi"), "hi")
    return edges, space


def scores(edges: DataFrame, space: SmallBiasSpace, members: list[int]) -> DataFrame:
    """(member, total, adjacent): pairs of edges in one class, and those that share a vertex, under each candidate."""
    two = lambda n: F.shiftright(n * (n - 1), 1).cast("decimal(38,0)")
    bit = lambda y, j: space.bit(F.col(y), j).cast("long")

    def by_member(sizes: DataFrame, name: str, pairs) -> DataFrame:
        """Sums over the groups of `pairs(i)`, the candidate's pairs in one group, as a row a candidate."""
        sums = sizes.agg(*[F.coalesce(F.sum(pairs(i)), F.lit(0)).cast("decimal(38,0)").alias(f"s{i}") for i in range(len(members))])
        rows = F.array(*[F.struct(F.lit(j).alias("member"), F.col(f"s{i}").alias(name)) for i, j in enumerate(members)])
        return sums.select(F.explode(rows).alias("row")).select("row.*")

    per_class = [F.sum(e).alias(f"{n}{i}") for i, j in enumerate(members) for n, e in (("lo", bit("y_lo", j)), ("hi", bit("y_hi", j)), ("both", bit("y_lo", j) * bit("y_hi", j)))]
    classes = edges.groupBy("x_lo", "x_hi").agg(F.count("*").alias("n"), *per_class)

    def split_class(i: int) -> Column:
        lo, hi, both = (F.col(f"{x}{i}") for x in ("lo", "hi", "both"))
        return two(both) + two(lo - both) + two(hi - both) + two(F.col("n") - lo - hi + both)

    end = lambda v, other, low: F.struct(F.col(v).alias("v"), F.col(f"y_{v}").alias("y"), F.col(f"y_{other}").alias("y_other"), F.lit(low).alias("low"))
    ends = edges.select("x_lo", "x_hi", F.explode(F.array(end("lo", "hi", 1), end("hi", "lo", 0))).alias("end")).select("x_lo", "x_hi", "end.*")
    per_vertex = [F.sum(e * bit("y_other", j)).alias(f"{n}{i}") for i, j in enumerate(members) for n, e in (("low", F.col("low")), ("high", 1 - F.col("low")))]
    vertices = ends.groupBy("x_lo", "x_hi", "v").agg(F.max("y").alias("y"), F.sum("low").alias("n_low"), F.sum(1 - F.col("low")).alias("n_high"), *per_vertex)

    def split_vertex(i: int) -> Column:
        own = bit("y", members[i]) == 1
        low, high = F.col(f"low{i}"), F.col(f"high{i}")
        # its edges whose other end has the same bit meet in one class, whichever end is lower; the rest do not
        same_low, same_high = F.when(own, low).otherwise(F.col("n_low") - low), F.when(own, high).otherwise(F.col("n_high") - high)
        return two(same_low + same_high) + two(F.col("n_low") - same_low) + two(F.col("n_high") - same_high)

    return by_member(classes, "total", split_class).join(by_member(vertices, "adjacent", split_vertex), "member")


def scaled_potential(level: int, c: int, apart: int, adjacent: int) -> int:
    """c^2 times the potential, in whole numbers."""
    return 4**level * apart + 2**level * c * adjacent


def scaled_cap(level: int, c: int, edges: int, m: int, alpha: float) -> Fraction:
    return (1 + Fraction(alpha).limit_denominator(10**6)) ** level * edges * m * c * c


def regrouped(state: DataFrame) -> DataFrame:
    """The edges stored in order of class and lower end.

    Ranges split a class over as many tasks as its edges ask for, and a task
    that scores the next level meets few classes, so it sends on few sums.
    """
    order = ("x_lo", "x_hi", "lo", "hi")
    return stored(state.repartitionByRange(*order).sortWithinPartitions(*order), "steered")


def choose_colouring(edges: DataFrame, space: SmallBiasSpace, c: int, total_edges: int, m: int, alpha: float, chunk: int = 8, accept: str = "first_chunk", regroup: bool = True) -> SteeredColouring:
    """Pick a member for each of log2 c levels.

    `first_chunk` stops at the first chunk whose best candidate keeps the
    potential under its cap; `exhaustive` scores the whole family; `first`
    takes the first candidate unscored, for comparison.  Some member keeps the
    potential under its cap if the space meets its bias, so the search goes on
    through the whole family; should none qualify, it raises.  `regroup` stores
    the edges by class after each bit; the bits chosen are the same without.
    """
    out = SteeredColouring(space, c)
    state = stored(edges.withColumn("x_lo", F.lit(1)).withColumn("x_hi", F.lit(1)), "steered")
    for level in range(1, c.bit_length()):
        cap = scaled_cap(level, c, total_edges, m, alpha)
        best: tuple[int, int, int, int] | None = None
        limit = space.size
        for at in range(0, 1 if accept == "first" else limit, 1 if accept == "first" else chunk):
            members = [at] if accept == "first" else list(range(at, min(at + chunk, limit)))
            for r in scores(state, space, members).collect():
                total, adjacent = int(r.total), int(r.adjacent)
                value = scaled_potential(level, c, total - adjacent, adjacent)
                best = min(x for x in (best, (value, r.member, total - adjacent, adjacent)) if x is not None)
            if accept != "exhaustive" and best is not None and best[0] <= cap:
                break
        if best is None:  # no edges
            best = (0, 0, 0, 0)
        if accept == "first_chunk" and best[0] > cap:
            raise ValueError(f"no member of the family keeps the potential of level {level} under its cap")
        out.members.append(best[1])
        out.potentials.append(best[0])
        out.caps.append(cap)
        out.apart.append(best[2])
        out.adjacent.append(best[3])
        step = lambda x, y: (2 * F.col(x) - space.bit(F.col(y), best[1])).cast("int")  # noqa: B023, E731
        state = state.withColumn("x_lo", step("x_lo", "y_lo")).withColumn("x_hi", step("x_hi", "y_hi"))
        if regroup and 2 << level <= c:
            state = regrouped(state)
    return out


def steered_classes(ranked: DataFrame, degrees: DataFrame, mm: MemoryModel, alpha: float | None = None, accept: str = "first_chunk", edges: int | None = None) -> tuple[DataFrame, DataFrame, SteeredColouring]:
    """(marked edges, low edges with classes k_lo and k_hi, the colouring)."""
    n = ranked.count() if edges is None else edges
    c = mm.colours(n, power_of_two=True)
    marked = mark_hubs(ranked, least_hub_degree(n, mm.m))
    low = marked.where(~touches_hub()) if c > 1 else marked
    a = default_alpha(c) if alpha is None else alpha
    columned, space = with_columns(low, degrees, a)
    columned = stored(columned, "columned")
    chosen = choose_colouring(columned, space, c, n, mm.m, a, accept=accept)
    classed = columned.select("lo", "hi", chosen.colour(F.col("y_lo")).alias("k_lo"), chosen.colour(F.col("y_hi")).alias("k_hi"))
    return marked, classed, chosen


def enumerate_steered(ranked: DataFrame, degrees: DataFrame, mm: MemoryModel, alpha: float | None = None, accept: str = "first_chunk", edges: int | None = None) -> DataFrame:
    """Every triangle (a, b, c) once, by a colouring that no chance went into."""
    marked, classed, chosen = steered_classes(ranked, degrees, mm, alpha, accept, edges)
    inner = join_kernel(classed, chosen.colours, edges=ranked.count() if edges is None else edges)
    return inner if chosen.colours == 1 else triangles_at_set(marked).unionByName(inner)
