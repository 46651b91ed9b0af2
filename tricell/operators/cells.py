"""Triangles by colour cells: hubs first, then one shuffle of coloured edges.

Vertices get one of c colours.  A triangle a < b < c of colours (p, q, r) is
met in cell (p, q, r) and nowhere else: its edges are sent there in three
roles.  Each cell's three inputs are joined inside the partition that the cell
lies in; the wedges on the way never leave their task.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.colours import colour, role_cell
from ..model import MemoryModel, co_partitioned
from .cone import triangles_at_set
from .hubs import least_hub_degree, mark_hubs, touches_hub

ROLES = ("tip_mid", "tip_top", "base")


@dataclass(frozen=True)
class CellPlan:
    """What the cell method decides before it starts."""

    edges: int
    memory: int
    colours: int
    least_hub: int
    seed: int = 1
    family: str = "poly4"

    @classmethod
    def make(cls, edges: int, mm: MemoryModel, seed: int = 1, family: str = "poly4", colours: int | None = None, power_of_two: bool = False) -> CellPlan:
        c = colours or mm.colours(edges, power_of_two)
        return cls(edges, mm.m, c, least_hub_degree(edges, mm.m), seed, family)


def coloured(edges: DataFrame, plan: CellPlan) -> DataFrame:
    """Edges with the colours of their ends, k_lo and k_hi: their class."""
    paint = lambda x: colour(F.col(x), plan.colours, plan.seed, plan.family)
    return edges.withColumn("k_lo", paint("lo")).withColumn("k_hi", paint("hi"))


def routed(classed: DataFrame, c: int, role: str) -> DataFrame:
    """(cell, lo, hi): each edge once for each cell that it serves in this role."""
    spread = classed.select("lo", "hi", "k_lo", "k_hi", F.explode(F.sequence(F.lit(0), F.lit(c - 1))).alias("free"))
    return spread.select(role_cell(role, F.col("k_lo"), F.col("k_hi"), F.col("free"), c).alias("cell"), "lo", "hi")


#: edges of one side that a task may hold as a hash table
HASHED_EDGES = 4_000_000
_PART_SEED = 7919


def partitions_for(spark: SparkSession, edges: int, c: int) -> int | None:
    """Partitions in which each side of the joins can be hashed; None if not even a cell alone is that small."""
    own = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    # each role holds c copies of the edges; four times the bound's room, as cells differ in size
    wanted = -(-4 * c * edges // HASHED_EDGES)
    if wanted > max(own, c**3):
        return None
    # some cells a task, so that no task waits for one that holds the largest ones
    return max(wanted, min(4 * own, 2 * c**3))


def parts_a_side(edges: int, c: int) -> int:
    """In how many parts the tips of a cell are dealt, and its tops, for each pair of parts to hold few enough edges a - c."""
    cells = -(-4 * edges // HASHED_EDGES)
    return max(2, -(-(isqrt(cells - 1) + 1) // c)) if cells > 1 else 2


def _in_parts(classed: DataFrame, c: int, f: int) -> DataFrame:
    """The joins inside cells, each cell dealt to f * f parts by its a and its c.

    An edge a - c lies in one part, so a task can hash its share; edges a - b and
    b - c are sent f times, sorted and merged.  Paths meet the hashed edges as
    they come and are never sorted.
    """
    # another seed than any cell's: the parts of a colour are to be alike
    part = lambda x: colour(F.col(x), f, _PART_SEED) - 1
    every = F.explode(F.sequence(F.lit(0), F.lit(f - 1)))
    tasks = max(int(classed.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 2 * c**3 * f * f)
    deal = lambda df: df.repartition(tasks, "cell", "part_a", "part_c")
    mid = deal(routed(classed, c, "tip_mid").toDF("cell", "a", "b").select("*", part("a").alias("part_a"), every.alias("part_c")))
    base = deal(routed(classed, c, "base").toDF("cell", "b", "c").select("*", part("c").alias("part_c"), every.alias("part_a")))
    top = deal(routed(classed, c, "tip_top").toDF("cell", "a", "c").select("*", part("a").alias("part_a"), part("c").alias("part_c")))
    own = ["cell", "part_a", "part_c"]
    return mid.join(base, [*own, "b"]).join(top.hint("shuffle_hash"), [*own, "a", "c"]).select("a", "b", "c")


def join_kernel(classed: DataFrame, c: int, partitions: int | None = None, edges: int | None = None) -> DataFrame:
    """Role-tagged joins inside cells: three exchanges on the cell, none after them.

    Paths a - b - c are met at b and closed by the edge a - c.  In rank order
    few edges leave a vertex that many enter, so these are fewer than the pairs
    of edges at the lowest vertex.  With the number of edges known, sides that
    fit in a task's memory are hashed, so that paths are never sorted.  Of cells
    that are too large for that, each is dealt in parts by its tips and tops.
    """
    hashed = partitions is None and edges is not None and (partitions := partitions_for(classed.sparkSession, edges, c)) is not None
    co_partitioned(classed.sparkSession)
    if partitions is None and edges is not None:
        return _in_parts(classed, c, parts_a_side(edges, c))
    deal = lambda df: df.repartition(partitions, "cell") if partitions else df.repartition("cell")
    names = {"tip_mid": ("a", "b"), "tip_top": ("a", "c"), "base": ("b", "c")}
    mid, top, base = (deal(routed(classed, c, r).toDF("cell", *names[r])) for r in ROLES)
    if hashed:
        base, top = base.hint("shuffle_hash"), top.hint("shuffle_hash")
    return mid.join(base, ["cell", "b"]).join(top, ["cell", "a", "c"]).select("a", "b", "c")


def _intersect(lo: np.ndarray, hi: np.ndarray, chunk: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Triangles of oriented edges, in bounded pieces: for each base (b, c), tips among b's predecessors."""
    ids, flat = np.unique(np.concatenate([lo, hi]), return_inverse=True)
    a, b = flat[: len(lo)], flat[len(lo) :]
    n = np.int64(len(ids))
    keys = np.unique(a * n + b)
    a, b = keys // n, keys % n
    starts = np.searchsorted(a, np.arange(n + 1))
    fan = starts[b + 1] - starts[b]
    ends = np.cumsum(fan)
    at = 0
    while at < len(a):
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + chunk, "right")))
        f = fan[at:to]
        first = np.repeat(np.arange(at, to), f)
        third = b[np.arange(f.sum()) - np.repeat(np.cumsum(f) - f, f) + np.repeat(starts[b[at:to]], f)]
        want = a[first] * n + third
        hit = keys[np.minimum(np.searchsorted(keys, want), len(keys) - 1)] == want
        yield ids[a[first[hit]]], ids[b[first[hit]]], ids[third[hit]]
        at = to


def arrow_kernel(classed: DataFrame, c: int) -> DataFrame:
    """Cells as in-memory batches: the union of the roles' edges, each at most once a cell.

    A cell must fit in a task's memory; `peak_cell` measures that.  A triangle
    is reported in the cell of its colours alone.
    """
    dealt = routed_once(classed, c)

    def solve(table: pa.Table) -> pa.Table:
        cell = table.column("cell")[0].as_py()
        p, q, r = cell // (c * c) + 1, cell // c % c + 1, cell % c + 1
        lo, hi = table.column("lo").to_numpy(), table.column("hi").to_numpy()
        ids, first = np.unique(np.concatenate([lo, hi]), return_index=True)
        shade = np.concatenate([table.column("k_lo").to_numpy(), table.column("k_hi").to_numpy()])[first]
        out = [[], [], []]
        for found in _intersect(lo, hi):
            keep = np.ones(len(found[0]), bool)
            for v, wanted in zip(found, (p, q, r), strict=True):
                keep &= shade[np.searchsorted(ids, v)] == wanted
            for k in range(3):
                out[k].append(found[k][keep])
        return pa.table({n: pa.array(np.concatenate(v) if v else [], pa.int64()) for n, v in zip("abc", out, strict=True)})

    return dealt.groupBy("cell").applyInArrow(solve, "a long, b long, c long")


def routed_once(classed: DataFrame, c: int, extra: Sequence[str] = ()) -> DataFrame:
    """(cell, lo, hi, k_lo, k_hi, extra): each edge once for each cell that needs it in any role: 3c - 2 copies."""
    own = lambda role: role_cell(role, F.col("k_lo"), F.col("k_hi"), F.col("free"), c)
    lo, hi, free = F.col("k_lo") - 1, F.col("k_hi") - 1, F.col("free")
    # where two roles of one edge name the same cell, only one of them keeps it
    top = F.when((free != lo) & (free != hi), own("tip_top"))
    base = F.when((lo != hi) | (free != lo), own("base"))
    spread = classed.select("lo", "hi", "k_lo", "k_hi", *extra, F.explode(F.sequence(F.lit(0), F.lit(c - 1))).alias("free"))
    named = spread.select("lo", "hi", "k_lo", "k_hi", *extra, F.explode(F.array_compact(F.array(own("tip_mid"), top, base))).alias("cell"))
    return named.select("cell", "lo", "hi", "k_lo", "k_hi", *extra)


#: edges of a cell whose triangles a task counts in memory
COUNTED_EDGES = 8_000_000
#: products of matrices take about as long for so many multiplications as a path does by itself
_DENSE_GAIN = 250
_DENSE_CELLS = 16_000_000
#: bytes of a table of the edges a - c of some a, and how many of its bytes are cleared as fast as a path is looked up otherwise
_TABLE_BYTES, _TABLE_GAIN = 1 << 22, 1000
#: edges that are packed at once
_PACKED_EDGES = 1 << 20


def counted_colours(edges: int, c: int) -> int:
    """At least c colours, and so many that a cell's 3 E / c^2 edges can be counted in memory."""
    return max(c, isqrt(max(0, -(-3 * edges // COUNTED_EDGES) - 1)) + 1)


def _dense_counts(sides: list, weights: list[np.ndarray]) -> list[np.ndarray]:
    """Weighted triangles at each a, b and c: sides are index pairs of a - b, a - c and b - c."""
    (ab_a, ab_b), (ac_a, ac_c), (bc_b, bc_c) = sides
    n = [len(w) for w in weights]
    wide = np.float32 if max(weights[1].sum(), weights[2].sum()) < 1 << 24 else np.float64
    base = np.zeros((n[1], n[2]), wide)
    base[bc_b, bc_c] = 1
    counts = [np.zeros(k, np.float64) for k in n]
    step = max(1, min(n[0], 512))
    for at in range(0, n[0], step):
        rows = min(step, n[0] - at)
        mid, top = np.zeros((rows, n[1]), wide), np.zeros((rows, n[2]), wide)
        own = (ab_a >= at) & (ab_a < at + rows)
        mid[ab_a[own] - at, ab_b[own]] = 1
        own = (ac_a >= at) & (ac_a < at + rows)
        top[ac_a[own] - at, ac_c[own]] = 1
        w_a = weights[0][at : at + rows].astype(np.float64)
        # for each a - b the weight of its tops, for each a - c that of its middles
        over_b = ((top * weights[2].astype(wide)) @ base.T) * mid
        counts[0][at : at + rows] = over_b.astype(np.float64) @ weights[1]
        counts[1] += w_a @ over_b
        counts[2] += w_a @ (((mid * weights[1].astype(wide)) @ base) * top)
    return counts


def _closed_paths(sides: list, n: list[int], marks: np.ndarray | None = None, chunk: int = 1 << 18) -> Iterator[tuple[np.ndarray, ...]]:
    """Paths a - b - c of a cell in bounded pieces: (edges a - b, paths of each, edges b - c, marks of the edges a - c).

    Edges are positions in the sides; a mark is 1, or as given, and 0 where
    the path is not closed.  Marks are read off a table of the edges a - c of
    some a at a time, or searched for where such a table were almost empty.
    """
    (ab_a, ab_b), (ac_a, ac_c), (bc_b, bc_c) = sides
    onward = np.argsort(bc_b, kind="stable").astype(np.int32)
    tops = bc_c[onward]
    starts = np.searchsorted(bc_b[onward], np.arange(n[1] + 1)).astype(np.int32)
    fan = starts[ab_b + 1] - starts[ab_b]
    order = np.argsort(ab_a, kind="stable")
    order = order[fan[order] > 0].astype(np.int32)
    if not len(order):
        return
    tips, first, fan = ab_a[order], starts[ab_b[order]], fan[order]
    ends = np.cumsum(fan, dtype=np.int64)
    marks = np.ones(len(ac_a), np.uint8) if marks is None else marks
    closing = np.argsort(ac_a * np.int64(n[2]) + ac_c)
    keys, marks = ac_a[closing] * np.int64(n[2]) + ac_c[closing], marks[closing]
    rows = max(1, _TABLE_BYTES // n[2])
    tabled = n[0] * n[2] < _TABLE_GAIN * int(ends[-1])
    at = 0
    while at < len(order):
        base = tips[at]
        stop = int(np.searchsorted(tips, base + rows)) if tabled else len(order)
        if tabled:
            table = np.zeros(min(rows, n[0] - int(base)) * n[2], marks.dtype)
            low, high = np.searchsorted(keys, [int(base) * n[2], (int(base) + rows) * n[2]])
            table[keys[low:high] - int(base) * n[2]] = marks[low:high]
        while at < stop:
            before = ends[at - 1] if at else 0
            to = min(stop, max(at + 1, int(np.searchsorted(ends, before + chunk, "right"))))
            f = fan[at:to]
            edge = np.arange(f.sum(), dtype=np.int32) + np.repeat(first[at:to] - (np.cumsum(f, dtype=np.int32) - f), f)
            if tabled:
                mark = table[np.repeat((tips[at:to] - base) * n[2], f) + tops[edge]]
            else:
                want = np.repeat(tips[at:to] * np.int64(n[2]), f) + tops[edge]
                place = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
                mark = np.where(keys[place] == want, marks[place], marks.dtype.type(0))
            yield order[at:to], f, onward[edge], mark
            at = to


def _path_counts(sides: list, weights: list[np.ndarray]) -> list[np.ndarray]:
    """The same by paths a - b - c, looked up among the edges a - c."""
    (ab_a, ab_b), _, (_, bc_c) = sides
    counts = [np.zeros(len(w), np.int64) for w in weights]
    plain = all((w == 1).all() for w in weights)
    for ab, fan, bc, mark in _closed_paths(sides, [len(w) for w in weights]):
        a, b = ab_a[ab], ab_b[ab]
        hit = np.flatnonzero(mark)
        if not len(hit):
            continue
        c = bc_c[bc[hit]]
        heads = np.cumsum(fan) - fan
        if plain:
            over = np.add.reduceat(mark, heads, dtype=np.int64)
            counts[2] += np.bincount(c, minlength=len(counts[2]))
        else:
            tops = np.zeros(len(mark), np.int64)
            tops[hit] = weights[2][c]
            over = np.add.reduceat(tops, heads)
            np.add.at(counts[2], c, np.repeat(weights[0][a] * weights[1][b], fan)[hit])
        np.add.at(counts[0], a, over * weights[1][b])
        np.add.at(counts[1], b, over * weights[0][a])
    return counts


_CORNERS = ((0, 1), (0, 2), (1, 2))


def _numbered(held: dict) -> tuple[list[np.ndarray], list]:
    """Sorted ids of each corner, and the sides with ends as positions among these; `held` has the ends of each side."""
    ids = [np.unique(np.concatenate([np.unique(held[s][s.index(corner)]) for s in _CORNERS if corner in s])) for corner in range(3)]
    return ids, [tuple(np.searchsorted(ids[k], held[s][i]).astype(np.int32) for i, k in enumerate(s)) for s in _CORNERS]


def _counts(held: dict) -> pa.Table:
    """(id, triangles) of a cell from the columns (lo, hi) or (lo, hi, w_lo, w_hi) of each of its sides."""
    if any(len(x[0]) == 0 for x in held.values()):
        return pa.table({"id": pa.array([], pa.int64()), "triangles": pa.array([], pa.int64())})
    ids, sides = _numbered(held)
    weights = [np.ones(len(v), np.int64) for v in ids]
    for s, ends in zip(_CORNERS, sides, strict=True):
        for k, at, w in zip(s, ends, held[s][2:]):
            weights[k][at] = w
    held.clear()  # numbers stand for the ids from here on
    leave = np.bincount(sides[2][0], minlength=len(ids[1]))
    paths = int(leave[sides[0][1]].sum())
    area = [len(v) for v in ids]
    dense = max(area[1] * area[2], 512 * max(area[1:])) <= _DENSE_CELLS and area[0] * area[1] * area[2] <= paths * _DENSE_GAIN
    # products are exact while sums stay under 2^53
    dense = dense and float(weights[0].sum()) * float(weights[1].sum()) * float(weights[2].sum()) < 2.0**53
    counts = (_dense_counts if dense else _path_counts)(sides, weights)
    out, n = np.concatenate(ids), np.concatenate(counts).astype(np.int64)
    return pa.table({"id": out[n > 0], "triangles": n[n > 0]})


def _shades(cell: int, c: int) -> tuple[int, int, int]:
    return cell // (c * c) + 1, cell // c % c + 1, cell % c + 1


def _cell_counts(table: pa.Table, c: int) -> pa.Table:
    """(id, triangles) of a cell's edges; triangles have the cell's colours."""
    shades = _shades(table.column("cell")[0].as_py(), c)
    names = ["lo", "hi", *(x for x in ("w_lo", "w_hi") if x in table.column_names)]
    k_lo, k_hi = (table.column(x).to_numpy() for x in ("k_lo", "k_hi"))
    own = {(i, j): (k_lo == shades[i]) & (k_hi == shades[j]) for i, j in _CORNERS}
    return _counts({s: tuple(table.column(x).to_numpy()[k] for x in names) for s, k in own.items()})


def _pack(columns: list[np.ndarray]) -> bytes:
    """Columns of longs, the first two being sorted edges, as their differences, equal bytes of all together."""
    order = np.lexsort((columns[1], columns[0]))
    steps = np.concatenate([np.diff(x[order].astype(np.int64), prepend=np.int64(0)) for x in columns])
    steps = steps << 1 ^ steps >> 63  # the sign last, so that small steps of either sign have few bytes
    return pa.compress(steps.view(np.uint8).reshape(-1, 8).T.tobytes(), codec="zstd", asbytes=True)


def _unpack(data: bytes, rows: int, columns: int) -> list[np.ndarray]:
    flat = np.frombuffer(pa.decompress(data, rows * columns * 8, codec="zstd"), np.uint8)
    steps = np.ascontiguousarray(flat.reshape(8, -1).T).view(np.uint64).reshape(columns, rows)
    steps = (steps >> np.uint64(1)).view(np.int64) ^ -(steps & np.uint64(1)).view(np.int64)
    return list(np.cumsum(steps, axis=1))


def packed_classes(classed: DataFrame, extra: Sequence[str] = ()) -> DataFrame:
    """(k_lo, k_hi, n, edges): the edges of each class in packed pieces, made where they are read, so that no edge is moved for it."""
    names = ["lo", "hi", *extra]

    def pieces(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held)
        cols = [table.column(x).to_numpy() for x in names]
        k_lo, k_hi = (table.column(x).to_numpy().astype(np.int64) for x in ("k_lo", "k_hi"))
        classes = k_lo << 32 | k_hi
        order = np.argsort(classes, kind="stable")
        found, heads = np.unique(classes[order], return_index=True)
        for k, own in zip(found, np.split(order, heads[1:]), strict=True):
            row = {"k_lo": [int(k) >> 32], "k_hi": [int(k) & 0xFFFFFFFF], "n": [len(own)], "edges": [_pack([x[own] for x in cols])]}
            yield pa.RecordBatch.from_pydict(row, pa.schema([("k_lo", pa.int32()), ("k_hi", pa.int32()), ("n", pa.int32()), ("edges", pa.binary())]))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= _PACKED_EDGES:
                yield from pieces(held)
                held, size = [], 0
        if size:
            yield from pieces(held)

    return classed.select("k_lo", "k_hi", *[F.col(x).cast("long").alias(x) for x in names]).mapInArrow(pack, "k_lo int, k_hi int, n int, edges binary")


def solve_packed(oriented: DataFrame, c: int, solve: Callable[[dict], pa.Table], schema: str, extra: Sequence[str] = (), seed: int = 1) -> DataFrame:
    """What `solve` gives for each cell, from the columns lo, hi and extra of its three sides.

    Edges are sent packed, a piece of a class to each of the 3 c - 2 cells that need it.
    """
    paint = lambda x: colour(F.col(x), c, seed)
    packed = packed_classes(oriented.select("lo", "hi", *extra, paint("lo").alias("k_lo"), paint("hi").alias("k_hi")), extra)
    # an edge of no ends stands for the class in the rules of which cells it goes to
    dealt = routed_once(packed.withColumns({"lo": F.lit(0), "hi": F.lit(0)}), c, ["n", "edges"])
    tasks = max(int(oriented.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), 2 * c**3)

    def cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = {s: [] for s in _CORNERS}
        for batch in batches:
            for row in batch.to_pylist():
                shades = _shades(row["cell"], c)
                found = _unpack(row["edges"], row["n"], 2 + len(extra))
                for i, j in _CORNERS:
                    if (row["k_lo"], row["k_hi"]) == (shades[i], shades[j]):
                        held[i, j].append(found)
        # sides of one class are one set of columns
        joined: dict[tuple[int, int], tuple] = {}
        sides = {}
        for i, j in _CORNERS:
            if not held[i, j]:
                return
            kind = shades[i], shades[j]
            if kind not in joined:
                joined[kind] = tuple(np.concatenate(x) for x in zip(*held[i, j], strict=True))
            sides[i, j] = joined[kind]
        held.clear()
        joined.clear()
        yield from solve(sides).to_batches()

    cell.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    return dealt.select("cell", "k_lo", "k_hi", "n", "edges").repartition(tasks, "cell").groupBy("cell").applyInArrow(cell, schema)


def vertex_counts(oriented: DataFrame, c: int, seed: int = 1, weighted: bool = False) -> DataFrame:
    """(id, triangles) of every vertex in a triangle of the oriented edges: cells count theirs in memory, no triangle is a row.

    A cell's edges must fit in a task's memory (`counted_colours`).  With
    weights w_lo and w_hi of an edge's ends, a triangle counts at each corner
    as the product of the other two weights.
    """
    found = solve_packed(oriented, c, _counts, "id long, triangles long", ["w_lo", "w_hi"] if weighted else [], seed)
    return found.groupBy("id").agg(F.sum("triangles").alias("triangles"))


def _last_counts(held: dict) -> pa.Table:
    """(last, triangles) of a cell by the greatest of a triangle's three labels, from the columns (lo, hi, label) of each side."""
    ids, sides = _numbered(held)
    labels = np.unique(np.concatenate([np.unique(x[2]) for x in held.values()]))
    small = np.uint8 if len(labels) < 255 else np.uint32
    ab_code, ac_code, bc_code = (np.searchsorted(labels, held[s][2]).astype(small) for s in _CORNERS)
    held.clear()
    counts = np.zeros(len(labels), np.int64)
    for ab, fan, bc, mark in _closed_paths(sides, [len(v) for v in ids], ac_code + small(1)):
        hit = np.flatnonzero(mark)
        last = np.maximum(mark[hit] - small(1), np.maximum(bc_code[bc[hit]], np.repeat(ab_code[ab], fan)[hit]))
        counts += np.bincount(last, minlength=len(labels))
    return pa.table({"last": labels[counts > 0], "triangles": counts[counts > 0]})


def last_counts(oriented: DataFrame, c: int, label: str, seed: int = 1) -> DataFrame:
    """(last, triangles): triangles by the greatest label, a long, of their edges; no triangle is a row."""
    found = solve_packed(oriented, c, _last_counts, "last long, triangles long", [label], seed)
    return found.groupBy("last").agg(F.sum("triangles").alias("triangles"))


def enumerate_cells(
    ranked: DataFrame, mm: MemoryModel, seed: int = 1, *, edges: int | None = None, colours: int | None = None, kernel: str = "join",
    hub_step: bool = True, family: str = "poly4", exactly_once: bool = True,
) -> DataFrame:
    """Every triangle (a, b, c) of the ranked edges once, a < b < c in rank order.

    The memory model sets the number of colours and what counts as a hub; it
    never changes the answer.  The one action on the way is the count of edges.
    """
    n = ranked.count() if edges is None else edges
    plan = CellPlan.make(n, mm, seed, family, colours)
    marked = mark_hubs(ranked, plan.least_hub)
    low = marked
    parts = []
    if hub_step and plan.colours > 1:
        parts.append(triangles_at_set(marked, exactly_once=exactly_once))
        low = marked.where(~touches_hub())
    classed = coloured(low.select("lo", "hi"), plan)
    parts.append(join_kernel(classed, plan.colours, edges=n) if kernel == "join" else arrow_kernel(classed, plan.colours))
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
