"""Cache-oblivious enumeration: recursive refinement of a colouring, level by level.

No function here takes a memory size.  All subproblems of one level lie in one
DataFrame keyed by their target triple; a level serves and removes each
subproblem's own hubs, refines the colours by one random bit a vertex, and
deals each edge to those of the eight children that it fits.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.colours import bit, bit_array, refined
from ..tables import shared_folder, stored
from .cells import join_kernel
from .cone import triangles_at_set
from .target import PLACES, compatible, fits, keyed_triangles

Z = ["z0", "z1", "z2"]
#: A vertex is a local hub if its degree times this reaches its subproblem's edges.
HUB_SHARE = 8


def root_level(ranked: DataFrame) -> DataFrame:
    """The whole graph as one subproblem of colour 1."""
    one = lambda name: F.lit(1).cast("int").alias(name)
    return ranked.select(*[one(z) for z in Z], "lo", "hi", "deg_lo", "deg_hi", one("x_lo"), one("x_hi"))


def local_hubs(level: DataFrame, sizes: DataFrame | None = None) -> DataFrame:
    """(z0, z1, z2, id, sub_deg, sub_edges): vertices with an eighth of their subproblem's edges or more.

    `sizes` has z0, z1, z2 and sub_edges, if they are known.
    """
    sizes = level.groupBy(*Z).agg(F.count("*").alias("sub_edges")) if sizes is None else sizes
    ends = level.select(*Z, F.explode(F.array("lo", "hi")).alias("id"))
    deg = ends.groupBy(*Z, "id").agg(F.count("*").alias("sub_deg"))
    return deg.join(sizes, Z).where(F.col("sub_deg") * HUB_SHARE >= F.col("sub_edges"))


def level_sizes(level: DataFrame) -> DataFrame:
    """Stored (z0, z1, z2, sub_edges) of the subproblems in which all three roles have an edge."""
    roles = [F.max(fits("x_lo", "x_hi", p).cast("int")) for p in PLACES]
    sizes = level.groupBy(*Z).agg(F.count("*").alias("sub_edges"), (roles[0] + roles[1] + roles[2]).alias("roles"))
    return stored(sizes.where("roles = 3").select(*Z, "sub_edges"), "sizes")


def mark_local_hubs(level: DataFrame, hubs: DataFrame) -> DataFrame:
    """The level's edges with hub_lo and hub_hi."""
    mark = lambda end: hubs.select(*Z, F.col("id").alias(end), F.lit(True).alias(f"hub_{end}"))
    joined = level.join(mark("lo"), [*Z, "lo"], "left").join(mark("hi"), [*Z, "hi"], "left")
    return joined.withColumn("hub_lo", F.coalesce("hub_lo", F.lit(False))).withColumn("hub_hi", F.coalesce("hub_hi", F.lit(False)))


def _colours_fit(depth: int, seed: int) -> Column:
    """Whether a hub and an edge have the subproblem's colours in rank order."""
    x_hub = refined(F.col("h"), depth, seed)
    hub, lo, hi = (F.col(f"{p}_point") for p in ("hub", "lo", "hi"))
    at = lambda z, edge: (x_hub == F.col(z)) & fits("x_lo", "x_hi", edge)
    return F.when(hub < lo, at("z0", PLACES[2])).when(hub > hi, at("z2", PLACES[0])).otherwise(at("z1", PLACES[1]))


def local_hub_triangles(marked: DataFrame, depth: int, seed: int) -> DataFrame:
    """Triangles with a local hub whose ordered colours are the subproblem's, each once."""
    return triangles_at_set(marked, Z, fits=_colours_fit(depth, seed))


def refine(level: DataFrame, depth: int, seed: int) -> DataFrame:
    """Each colour x becomes 2x or 2x - 1, by the level's bit of its vertex."""
    step = lambda x, v: (2 * F.col(x) - bit(F.col(v), depth, seed)).cast("int")
    return level.withColumn("x_lo", step("x_lo", "lo")).withColumn("x_hi", step("x_hi", "hi"))


def child_triples(level: DataFrame) -> DataFrame:
    """Each row once for each of the eight children of its triple."""
    options = [F.struct(*[(2 * F.col(z) - ((k >> s) & 1)).cast("int").alias(z) for s, z in enumerate(Z)]) for k in range(8)]
    rest = [c for c in level.columns if c not in Z]
    return level.select(F.explode(F.array(*options)).alias("child"), *rest).select("child.*", *rest)


def split_children(level: DataFrame) -> DataFrame:
    """Edges under refined colours, dealt to the children of their subproblem that they fit."""
    return child_triples(level).where(compatible())


def live_subproblems(level: DataFrame) -> DataFrame:
    """The edges of subproblems in which all three roles have an edge."""
    roles = [F.max(fits("x_lo", "x_hi", p).cast("int")) for p in PLACES]
    keys = level.groupBy(*Z).agg((roles[0] + roles[1] + roles[2]).alias("roles")).where("roles = 3").select(*Z)
    return level.join(keys, Z, "left_semi")


@dataclass
class Trace:
    """What each level held; filled while the method runs."""

    rows: list[int] = field(default_factory=list)
    subproblems: list[int] = field(default_factory=list)


class Found:
    """Triangles of a run, stored level by level in one folder and read as one table."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.path = spark, f"{shared_folder(spark)}/found-{uuid.uuid4().hex}"

    def add(self, triangles: DataFrame) -> None:
        triangles.select("a", "b", "c").write.mode("append").parquet(self.path)

    def table(self) -> DataFrame:
        return self.spark.read.schema("a long, b long, c long").parquet(self.path)


def max_depth(edges: int) -> int:
    """floor(log4 E)."""
    return (max(edges, 1).bit_length() - 1) // 2


def levels(ranked: DataFrame, seed: int, depth: int, local_hub_step: bool = True, prune: bool = True) -> list[DataFrame]:
    """The levels 0..depth before their hubs are removed, for measures."""
    out = [root_level(ranked)]
    for i in range(1, depth + 1):
        level = out[-1]
        if local_hub_step:
            marked = mark_local_hubs(level, local_hubs(level))
            level = marked.where("not hub_lo and not hub_hi").drop("hub_lo", "hub_hi")
        level = split_children(refine(level, i, seed))
        out.append(stored(live_subproblems(level) if prune else level, "level"))
    return out


def enumerate_recursive(ranked: DataFrame, seed: int = 1, base_size: int = 64, depth: int | None = None, local_hub_step: bool = True, trace: Trace | None = None) -> DataFrame:
    """Every triangle (a, b, c) once.

    Subproblems of at most `base_size` edges, a constant, and those of the
    last level are solved by sorting.  A level is stored, and one pass over it
    gives the size of each subproblem and the roles that it has edges for; the
    hub step is passed over where a level has no local hub.  What a level
    finds is stored with it, so that no plan spans more than one level.
    Subproblems that a task can hold are solved by it to the end of the
    recursion, depth first, so that few levels are left to the driver; with a
    trace every level is stored, as it tells of each.
    """
    held = max(base_size, TASK_EDGES) if trace is None else base_size
    level = stored(root_level(ranked), "level")
    last = max_depth(level.count()) if depth is None else depth
    parts = Found(level.sparkSession)
    for i in range(last + 1):
        if i < last:
            sizes = level_sizes(level)
            counts = sizes.agg(F.count("*").alias("live"), F.count_if(F.col("sub_edges") > held).alias("large"), F.sum("sub_edges").alias("rows")).first()
            found, large = (counts.live, counts.rows or 0), counts.large
            small = level if not large else level.join(sizes.where(F.col("sub_edges") <= held).select(*Z), Z, "left_semi")
        else:
            found, large, small = None, 0, level
        if trace is not None:
            found = found or tuple(level_sizes(level).agg(F.count("*"), F.coalesce(F.sum("sub_edges"), F.lit(0))).first())
            trace.rows.append(found[1])
            trace.subproblems.append(found[0])
        whole = trace is None and i < last
        parts.add(depth_first(small, i, last, base_size, seed, local_hub_step) if whole else keyed_triangles(small))
        if not large:
            break
        wide = sizes.where(F.col("sub_edges") > held)
        level = level.join(wide.select(*Z), Z, "left_semi")
        hubs = stored(local_hubs(level, wide.select(*Z, "sub_edges")), "local-hubs") if local_hub_step else None
        if hubs is not None and not hubs.isEmpty():
            marked = stored(mark_local_hubs(level, hubs), "marked")
            parts.add(local_hub_triangles(marked, i, seed))
            level = marked.where("not hub_lo and not hub_hi").drop("hub_lo", "hub_hi")
        level = stored(split_children(refine(level, i + 1, seed)), "level")
    return parts.table()


def shared_view(edges: DataFrame, live: DataFrame, removed: list[tuple[int, DataFrame]], depth: int, seed: int) -> DataFrame:
    """A level's edges by subproblem, read off the one stored copy of the edges.

    An edge belongs to the live subproblems that its colours fit, unless one of
    its ends was a local hub of the subproblem or of one it descends from;
    `removed` has the hubs (z0, z1, z2, id) of each level before.
    """
    painted = edges.withColumn("x_lo", refined(F.col("lo"), depth, seed)).withColumn("x_hi", refined(F.col("hi"), depth, seed))
    asked = F.array_distinct(F.array(*[F.struct(F.col(p).alias("x_lo"), F.col(q).alias("x_hi")) for p, q in PLACES]))
    view = painted.join(live.select(*Z, F.explode(asked).alias("asked")).select(*Z, "asked.*"), ["x_lo", "x_hi"])
    for at, hubs in removed:
        for end in ("lo", "hi"):
            gone = hubs.toDF(*[f"up_{z}" for z in Z], "gone")
            above = [F.shiftright(F.col(z) - 1, depth - at) + 1 == F.col(f"up_{z}") for z in Z]
            view = view.join(gone, reduce(Column.__and__, above, F.col(end) == F.col("gone")), "left_anti")
    return view.select(*Z, "lo", "hi", "deg_lo", "deg_hi", "x_lo", "x_hi")


#: edges of a subproblem that one task solves to its end
TASK_EDGES = 1 << 20
#: paths that a task closes at once, and triangles of a batch that it passes on
_PATHS_AT_ONCE, _BATCH = 1 << 20, 1 << 16
_PLACES = ((0, 1), (0, 2), (1, 2))


def _closed(lo: np.ndarray, hi: np.ndarray, held: list[np.ndarray], n: int) -> Iterator[tuple[np.ndarray, ...]]:
    """The triangles of a subproblem's edges by role, in bounded pieces; ends are numbers below n."""
    mid, top, base = held
    a, b = lo[mid], hi[mid]
    bases, closing = np.sort(lo[base] * n + hi[base]), np.sort(lo[top] * n + hi[top])
    first, tops = np.searchsorted(bases, b * n), bases % n
    fan = np.searchsorted(bases, (b + 1) * n) - first
    ends = np.cumsum(fan)
    at = 0
    while at < len(a):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + _PATHS_AT_ONCE, "right")))
        f = fan[at:to]
        row = np.repeat(np.arange(at, to), f)
        c = tops[np.arange(f.sum()) - np.repeat(np.cumsum(f) - f, f) + np.repeat(first[at:to], f)]
        want = a[row] * n + c
        hit = closing[np.minimum(np.searchsorted(closing, want), len(closing) - 1)] == want
        yield a[row[hit]], b[row[hit]], c[hit]
        at = to


class _DepthFirst:
    """The recursion of one subproblem in the memory of a task: children are solved one after another, on their parent's edges.

    Vertices are numbered in rank order.  `shades` has the vertices' colours of each level from `depth` on.
    """

    def __init__(self, ids: np.ndarray, shade: np.ndarray, depth: int, last: int, base_size: int, seed: int, hubs: bool = True) -> None:
        self.ids, self.depth, self.last, self.base_size, self.seed, self.hubs = ids, depth, last, base_size, seed, hubs
        self.shades = [shade.astype(np.int64)]

    def shade(self, level: int) -> np.ndarray:
        while len(self.shades) <= level - self.depth:
            self.shades.append(2 * self.shades[-1] - bit_array(self.ids, self.depth + len(self.shades), self.seed))
        return self.shades[level - self.depth]

    def solve(self, level: int, z: tuple[int, ...], lo: np.ndarray, hi: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        n, x = len(self.ids), self.shade(level)
        held = [(x[lo] == z[i]) & (x[hi] == z[j]) for i, j in _PLACES]
        if not all(h.any() for h in held):
            return
        if len(lo) <= self.base_size or level == self.last:
            yield from _closed(lo, hi, held, n)
            return
        degrees = np.bincount(lo, minlength=n) + np.bincount(hi, minlength=n)
        # the highest hub first, and its edges go: a triangle is credited to its highest hub
        for h in np.flatnonzero(degrees * HUB_SHARE >= len(lo))[::-1] if self.hubs else ():
            near = np.zeros(n, bool)
            near[hi[lo == h]] = near[lo[hi == h]] = True
            both = near[lo] & near[hi]
            u, v = lo[both], hi[both]
            corners = np.sort(np.stack([np.full(len(u), h), u, v]), axis=0)
            fit = (x[corners] == np.array(z)[:, None]).all(axis=0)
            yield tuple(corners[:, fit])
            rest = (lo != h) & (hi != h)
            lo, hi = lo[rest], hi[rest]
        x = self.shade(level + 1)
        x_lo, x_hi = x[lo], x[hi]
        for k in range(8):
            child = tuple(2 * c - ((k >> s) & 1) for s, c in enumerate(z))
            fit = reduce(np.logical_or, [(x_lo == child[i]) & (x_hi == child[j]) for i, j in _PLACES])
            if fit.any():
                yield from self.solve(level + 1, child, lo[fit], hi[fit])


def _finish(batches: Iterator[pa.RecordBatch], depth: int, last: int, base_size: int, seed: int, hubs: bool) -> Iterator[pa.RecordBatch]:
    """The triangles (a, b, c) of one subproblem's edges."""
    table = pa.Table.from_batches(batches)
    z = tuple(table.column(name)[0].as_py() for name in Z)
    both = lambda name: np.concatenate([table.column(f"{name}lo").to_numpy(), table.column(f"{name}hi").to_numpy()])
    ids, first, flat = np.unique(both(""), return_index=True, return_inverse=True)
    order = np.lexsort((ids, both("deg_")[first]))
    rank = np.empty(len(ids), np.int64)
    rank[order] = np.arange(len(ids))
    ends, ids, shade = rank[flat], ids[order], both("x_")[first][order]
    found, size = [], 0
    m = table.num_rows
    del table
    for piece in _DepthFirst(ids, shade, depth, last, base_size, seed, hubs).solve(depth, z, ends[:m], ends[m:]):
        found.append(piece)
        size += len(piece[0])
        if size >= _BATCH:
            yield pa.RecordBatch.from_arrays([pa.array(ids[np.concatenate(v)]) for v in zip(*found, strict=True)], list("abc"))
            found, size = [], 0
    if size:
        yield pa.RecordBatch.from_arrays([pa.array(ids[np.concatenate(v)]) for v in zip(*found, strict=True)], list("abc"))


def depth_first(level: DataFrame, depth: int, last: int, base_size: int, seed: int, hubs: bool = True) -> DataFrame:
    """The triangles of each subproblem of a level, each solved to the end of the recursion by one task."""

    # by these annotations Spark passes batches on as they are found
    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _finish(batches, depth, last, base_size, seed, hubs)

    solve.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    tasks = max(int(level.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 8 ** min(depth, 3))
    return level.repartition(tasks, *Z).groupBy(*Z).applyInArrow(solve, "a long, b long, c long")


def enumerate_shared(ranked: DataFrame, seed: int = 1, base_size: int = 64, depth: int | None = None) -> DataFrame:
    """Every triangle (a, b, c) once, with all subproblems on one copy of the edges.

    The recursion of `enumerate_recursive`, hubs included, but no subproblem is
    stored: a level keeps its live triples and its local hubs, at most sixteen
    a subproblem, so storage stays at O(E) words where the other may need a
    log E times that.  Each use of a level reads the edges again.  All branches
    of a level run together until a task can hold a subproblem, which it then
    solves depth first.
    """
    edges = stored(ranked.select("lo", "hi", "deg_lo", "deg_hi"), "shared")
    last = max_depth(edges.count()) if depth is None else depth
    live = edges.sparkSession.createDataFrame([(1, 1, 1)], "z0 int, z1 int, z2 int")
    removed: list[tuple[int, DataFrame]] = []
    parts: list[DataFrame] = []
    for i in range(last + 1):
        level = shared_view(edges, live, removed, i, seed)
        if i == last:
            parts.append(keyed_triangles(level).select("a", "b", "c"))
            break
        sizes = level_sizes(level)
        held = max(base_size, TASK_EDGES)
        small, wide = (sizes.where(F.col("sub_edges") <= held), sizes.where(F.col("sub_edges") > held))
        parts.append(depth_first(level.join(small.select(*Z), Z, "left_semi"), i, last, base_size, seed))
        if wide.isEmpty():
            break
        hubs = stored(local_hubs(level.join(wide.select(*Z), Z, "left_semi"), wide), "local-hubs")
        if not hubs.isEmpty():
            marked = mark_local_hubs(level.join(wide.select(*Z), Z, "left_semi"), hubs)
            parts.append(local_hub_triangles(marked, i, seed).select("a", "b", "c"))
            removed.append((i, hubs.select(*Z, "id")))
        live = stored(child_triples(wide), "live")
    return reduce(DataFrame.unionByName, parts)


def level_cells(ranked: DataFrame, depth: int, seed: int) -> DataFrame:
    """Cells of one level straight from the edges: colours are a closed form, so no level before it is stored.

    Removal of local hubs is left out, which costs space in no level but this one.
    """
    c = 1 << depth
    painted = ranked.select("lo", "hi", refined(F.col("lo"), depth, seed).alias("k_lo"), refined(F.col("hi"), depth, seed).alias("k_hi"))
    return join_kernel(painted, c)


def stub_edges(level: DataFrame, hubs: DataFrame) -> DataFrame:
    """Edges in which each local hub is replaced by a copy of degree one; no edge is lost (for measures)."""
    marked = mark_local_hubs(level, hubs)
    stub = lambda end: F.when(F.col(f"hub_{end}"), -1 - F.pmod(F.xxhash64("lo", "hi", F.lit(end)), F.lit(1 << 62))).otherwise(F.col(end))
    return marked.withColumn("s_lo", stub("lo")).withColumn("s_hi", stub("hi"))
