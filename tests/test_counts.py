"""Triangles that are counted where they are found, and jobs that must not grow with their product."""

from collections import Counter
from itertools import combinations
from random import Random

import numpy as np
import pytest

from tricell import catalog
from tricell.operators import cells, twins
from tricell.streaming import incremental


def brute_counts(pairs, weight=lambda v: 1):
    """(id, triangles) of the pairs; a triangle counts as the product of the other two weights."""
    near = {}
    for u, v in pairs:
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    found = Counter()
    for u, v in {tuple(sorted(p)) for p in pairs}:
        for w in near[u] & near[v]:
            if w > v:
                for x, y, z in ((u, v, w), (v, u, w), (w, u, v)):
                    found[x] += weight(y) * weight(z)
    return dict(found)


def test_members_of_one_group_are_not_linked(spark):
    """20,000 members of a group have 2e8 pairs and 1.3e12 triangles."""
    n = 20_000
    rows = spark.range(n).selectExpr("'all' as k", "id as m").unionByName(spark.createDataFrame([("odd", 5), ("odd", n + 7), (None, 1), ("alone", 3)], "k string, m long"))
    got = twins.vertex_triangles(rows, ["k"], "m", 2)
    each = (n - 1) * (n - 2) // 2
    assert [tuple(r) for r in got.groupBy("triangles").count().collect()] == [(each, n)]


def test_twins_equal_brute_force(spark):
    r = Random(3)
    rows = [(r.randrange(12), r.choice("xyz"), m) for m in range(60) for _ in range(r.randrange(4))]
    rows += [(a, b, m + 100) for a, b, m in rows if m % 3]  # twins
    rows += rows[:20] + [(None, "x", 1), (1, None, 2), (1, "x", None)]
    groups = {}
    for a, b, m in rows:
        if None not in (a, b, m):
            groups.setdefault((a, b), set()).add(m)
    want = brute_counts({p for g in groups.values() for p in combinations(sorted(g), 2)})
    df = spark.createDataFrame(rows, "a int, b string, m long")
    for c in (1, 2, 3):
        assert {x.id: x.triangles for x in twins.vertex_triangles(df, ["a", "b"], "m", c).collect()} == want


@pytest.mark.parametrize("dense", [False, True])
@pytest.mark.parametrize("c", [1, 3])
def test_counts_in_cells_equal_brute_force(spark, monkeypatch, c, dense):
    monkeypatch.setattr(cells, "_DENSE_GAIN", 1e9 if dense else 0)
    r = Random(4)
    pairs = {tuple(sorted(r.sample(range(40), 2))) for _ in range(300)}
    weight = lambda v: v % 5 + 1
    df = spark.createDataFrame([(u, v, weight(u), weight(v)) for u, v in pairs], "lo long, hi long, w_lo long, w_hi long")
    # the limit is set in the driver, so the kernel is called here
    for weighted in (False, True):
        found = Counter()
        one = cells.routed_once(df.select("lo", "hi", *(["w_lo", "w_hi"] if weighted else []), cells.colour(df.lo, c, 1).alias("k_lo"), cells.colour(df.hi, c, 1).alias("k_hi")), c, ["w_lo", "w_hi"] if weighted else [])
        table = one.toArrow()
        for cell in set(table.column("cell").to_pylist()):
            own = cells._cell_counts(table.filter(np.array(table.column("cell")) == cell), c)
            for v, n in zip(*[own.column(x).to_pylist() for x in ("id", "triangles")], strict=True):
                found[v] += n
        assert dict(found) == brute_counts(pairs, weight if weighted else lambda v: 1)


def test_triangles_of_a_complete_graph_are_not_rows(spark):
    """600 vertices have 36 million triangles; no operator gives so many rows."""
    n = 600
    o = spark.range(n).selectExpr("id as lo").crossJoin(spark.range(n).selectExpr("id as hi")).where("lo < hi")
    got = cells.vertex_counts(o, 2)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "ShuffledHashJoin" not in plan
    assert [tuple(r) for r in got.groupBy("triangles").count().collect()] == [((n - 1) * (n - 2) // 2, n)]


@pytest.mark.parametrize("name", ["w_docline", "w_labelled_docs", "w_pages", "w_nation_cliques", "w_clique", "w_coact"])
def test_counts_equal_their_sql(spark, sf_dir, duck, name):
    got = sorted((r.id, r.triangles) for r in catalog.queries()[name](spark, sf_dir).collect())
    assert got == sorted(duck.execute(f"select id, triangles from ({catalog.oracle_sql()[name]})").fetchall())


@pytest.mark.parametrize("kind", ["timestamp", "timestamp_ntz"])
def test_interval_join_meets_rows_of_near_buckets_alone(spark, kind):
    """Rows of one key far apart in time are no candidates: the join has the bucket among its keys."""
    from tricell.streaming import windows

    rows = spark.sql(f"select 'a' as k, id as n, cast(timestamp'1969-12-31 23:50:00' + make_dt_interval(0, 0, 0, id * 0.5) as {kind}) as ts from range(2000)")
    near = windows.interval_join(rows, rows, ["k"], "ts", 7)
    got = {(r.left_n, r.right_n) for r in near.collect()}
    assert near.count() == len(got)
    assert got == {(x, y) for x in range(2000) for y in range(max(0, x - 14), min(2000, x + 15))}
    assert near.columns == ["k", "left_n", "left_ts", "right_n", "right_ts"]
    joins = [x for x in near._jdf.queryExecution().executedPlan().toString().split("\n") if "Join [" in x]
    assert joins and all("bucket_" in x for x in joins)


def _joins(df):
    return df._jdf.queryExecution().analyzed().toString().count("Join ")


def test_recursion_gives_one_stored_table(spark):
    """What each level finds is stored with it: the result's plan has no join of any level."""
    from tricell.operators import canonical, recursive

    pairs = spark.createDataFrame([(u, v) for u in range(12) for v in range(u)], "u long, v long")
    r = canonical.orient(canonical.canonical_edges(pairs), keep_degrees=True).cache()
    got = recursive.enumerate_recursive(r, base_size=8)
    assert _joins(got) == 0
    assert got.count() == got.distinct().count() == 12 * 11 * 10 // 6
    assert recursive.enumerate_recursive(r.limit(0), base_size=8).count() == 0


def test_packed_edges_come_back():
    lo = np.array([5, -(2**63), 2**63 - 1, 5, 0], np.int64)
    hi = np.array([7, 2**63 - 1, -4, 6, 2**40], np.int64)
    got = cells._unpack(cells._pack([lo, hi, np.arange(5)]), 5, 3)
    assert sorted(zip(*[x.tolist() for x in got], strict=True)) == sorted(zip(lo.tolist(), hi.tolist(), range(5), strict=True))


@pytest.mark.parametrize(("table", "gain"), [(1 << 22, 1e9), (64, 1e9), (1 << 22, 0)])
def test_paths_are_closed_by_tables_or_by_search(monkeypatch, table, gain):
    """Tables of all, of few and of no vertices, pieces of any size, and weights."""
    monkeypatch.setattr(cells, "_TABLE_BYTES", table)
    monkeypatch.setattr(cells, "_TABLE_GAIN", gain)
    monkeypatch.setattr(cells, "_DENSE_GAIN", 0)
    r = Random(6)
    pairs = {tuple(sorted(r.sample(range(50), 2))) for _ in range(400)}
    lo, hi = (np.array(x) * 3 - 40 for x in zip(*pairs, strict=True))
    weight = lambda v: (v + 40) % 5 + 1
    for extra, w in (((), lambda v: 1), ((weight(lo), weight(hi)), weight)):
        got = Counter()
        found = cells._counts({s: (lo, hi, *extra) for s in cells._CORNERS})
        for v, n in zip(found.column("id").to_pylist(), found.column("triangles").to_pylist(), strict=True):
            got[v] += n
        assert dict(got) == brute_counts(list(zip(lo.tolist(), hi.tolist(), strict=True)), w)


def test_cells_are_sent_packed_edges(spark):
    """Of 20,000 edges, each needed in 13 cells, 260,000 rows would be sent one by one; here a few pieces are."""
    o = spark.range(20_000).selectExpr("id % 200 as lo", "200 + id as hi")
    packed = cells.packed_classes(o.selectExpr("lo", "hi", "cast(lo % 5 + 1 as int) as k_lo", "cast(hi % 5 + 1 as int) as k_hi"))
    rows = packed.collect()
    assert sum(x.n for x in rows) == 20_000 and len(rows) <= 25 * o.rdd.getNumPartitions()
    assert sum(len(x.edges) for x in rows) < 8 * 20_000
    assert "edges#" in cells.vertex_counts(o, 5)._jdf.queryExecution().executedPlan().toString()


def test_triangles_of_close_vectors_are_not_rows(spark, sf_dir, duck):
    got = catalog.queries()["w_vec"](spark, sf_dir)
    plan = got._jdf.queryExecution().executedPlan().toString()
    # two joins give edges their degrees; none closes paths
    assert plan.count("Join") <= 2 and "FlatMapGroupsInArrow" in plan
    assert sorted(map(tuple, got.collect())) == sorted(duck.execute(catalog.oracle_sql()["w_vec"]).fetchall())


@pytest.mark.parametrize("batches", [1, 5, 300])
def test_replay_counts_triangles_where_they_are_found(spark, batches):
    """By brute force, an edge of no batch comes before all others; no join closes paths."""
    r = Random(8)
    pairs = sorted({tuple(sorted(r.sample(range(60), 2))) for _ in range(700)})
    at = {p: None if k % 50 < 4 else r.randrange(batches) - 1 for k, p in enumerate(pairs)}
    got = incremental.replay(spark.createDataFrame([(*p, n) for p, n in at.items()], "u long, v long, n int"), "n", batches)
    want = Counter()
    for u, v in pairs:
        for w in range(v + 1, 60):
            if (v, w) in at and (u, w) in at:
                want[max((at[e] for e in ((u, v), (v, w), (u, w)) if at[e] is not None), default=None)] += 1
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Join") <= 2 and "FlatMapGroupsInArrow" in plan
    assert {x.batch: x.triangles for x in got.collect()} == dict(want) and dict(got.dtypes) == {"batch": "int", "triangles": "bigint"}


def test_suppliers_of_one_order_are_sent_packed(spark, sf_dir, duck):
    """Edges of `w_clique` are packed where they are read and not stored or sent one by one for each cell."""
    got = catalog.queries()["w_clique"](spark, sf_dir)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "edges#" in plan.split("MapInArrow")[0]
    assert sorted(map(tuple, got.collect())) == sorted(duck.execute(catalog.oracle_sql()["w_clique"]).fetchall())
