"""Cliques grown in memory: exact for any piece size and number of cells, and no partial clique is moved."""

from itertools import combinations
from math import comb

import numpy as np
import pytest
from pyspark.sql import functions as F

from tricell.functions.colours import bit, bit_array
from tricell.operators import baselines, canonical, cliques, recursive
from tricell.sources import generate


def brute(pairs, k):
    linked = {frozenset(p) for p in pairs}
    vertices = sorted({v for p in pairs for v in p})
    return {c for c in combinations(vertices, k) if all(frozenset(p) in linked for p in combinations(c, 2))}


@pytest.fixture(scope="module")
def dense(spark):
    e = canonical.canonical_edges(generate.random_pairs(spark, 16, 160, 5))
    return canonical.orient(e), [(r.u, r.v) for r in e.collect()]


@pytest.mark.parametrize("pair_bytes", [0, 1 << 20])
@pytest.mark.parametrize("at_once", [1, 7, 1 << 19])
def test_pieces_of_any_size_give_each_clique_once(monkeypatch, pair_bytes, at_once):
    monkeypatch.setattr(cliques, "PAIR_BYTES", pair_bytes)
    monkeypatch.setattr(cliques, "GROWN_AT_ONCE", at_once)
    lo, hi = np.array(list(combinations(range(9), 2))).T
    for k in (3, 4, 5):
        pieces = [f for part in range(3) for f in cliques._grow(lo, hi, np.ones(9, np.int32), [1] * k, part, 3)]
        found = [tuple(int(x) for x in c) for f in pieces for c in zip(*f, strict=True)]
        assert len(found) == len(set(found)) == comb(9, k)
        if at_once < 8:
            # a vertex's own fan is the least piece
            assert max(len(f[0]) for f in pieces) <= at_once + 8


@pytest.mark.parametrize(("k", "held"), [(3, 40), (4, 70), (5, 8_000_000)])
def test_cliques_equal_brute_force_and_move_edges_alone(spark, dense, monkeypatch, k, held):
    edges, pairs = dense
    # with few edges a task, cells get more colours than asked for
    monkeypatch.setattr(cliques, "HELD_EDGES", held)
    wanted = brute(pairs, k)
    for df in (cliques.enumerate_cliques(edges, k, colours=2), cliques.cliques_by_growth(edges, k)):
        found = [tuple(sorted(r)) for r in df.collect()]
        assert len(found) == len(set(found)) and set(found) == wanted
        # nothing is joined or dealt anew after cliques are found
        assert df._jdf.queryExecution().optimizedPlan().toString().startswith("FlatMapGroupsInArrow")



@pytest.mark.parametrize("block", [2_000_000, 40])
def test_nested_loops_compare_no_two_edges_without_need(spark, dense, monkeypatch, block):
    edges, pairs = dense
    monkeypatch.setattr(baselines, "BLOCK_EDGES", block)
    monkeypatch.setattr(baselines, "OUTER_PIECES", 2)
    df = baselines.nested_loop_triangles(edges)
    found = [tuple(sorted(r)) for r in df.collect()]
    assert len(found) == len(set(found)) and set(found) == brute(pairs, 3)
    # no join of all edges with all edges
    assert "Join Inner" not in df._jdf.queryExecution().optimizedPlan().toString().split("Union")[0]


def test_bits_in_memory_are_those_of_the_columns(spark):
    ids = [0, 1, 5, 2**31 - 2, 2**31 - 1, 2**31, 2**61 - 1, 2**62, -1, -(2**40)]
    rows = spark.createDataFrame([(i,) for i in ids], "id long").select("id", *[bit(F.col("id"), k, 7).alias(f"b{k}") for k in (1, 2, 9)]).collect()
    for k in (1, 2, 9):
        assert bit_array(np.array([r.id for r in rows]), k, 7).tolist() == [r[f"b{k}"] for r in rows]


@pytest.mark.parametrize("held", [recursive.TASK_EDGES, 60])
def test_subproblems_that_a_task_holds_are_solved_there(spark, dense, monkeypatch, held):
    """Two hubs beside a dense graph; the levels before a task's share are those of the whole."""
    monkeypatch.setattr(recursive, "TASK_EDGES", held)
    pairs = dense[1] + [(100, i) for i in range(16)] + [(i, 101) for i in range(16)] + [(100, 101)]
    ranked = canonical.orient(canonical.canonical_edges(spark.createDataFrame(pairs, "u long, v long")), keep_degrees=True).cache()
    levels = []
    view = recursive.shared_view
    monkeypatch.setattr(recursive, "shared_view", lambda *args: levels.append(args[3]) or view(*args))
    found = [tuple(sorted(r)) for r in recursive.enumerate_shared(ranked, base_size=8).collect()]
    assert len(found) == len(set(found)) and set(found) == brute(pairs, 3)
    # a graph that a task holds needs no level of its own
    assert levels == [0] if held > 60 else len(levels) > 1


@pytest.mark.parametrize("hubs", [True, False])
@pytest.mark.parametrize("held", [recursive.TASK_EDGES, 60])
def test_stored_levels_end_where_a_task_holds_a_subproblem(spark, dense, monkeypatch, held, hubs):
    """With and without the hub step; the driver plans no level of a graph that a task holds."""
    monkeypatch.setattr(recursive, "TASK_EDGES", held)
    pairs = dense[1] + [(100, i) for i in range(16)] + [(i, 101) for i in range(16)] + [(100, 101)]
    ranked = canonical.orient(canonical.canonical_edges(spark.createDataFrame(pairs, "u long, v long")), keep_degrees=True).cache()
    depths = []
    refine = recursive.refine
    monkeypatch.setattr(recursive, "refine", lambda level, i, seed: depths.append(i) or refine(level, i, seed))
    found = [tuple(sorted(r)) for r in recursive.enumerate_recursive(ranked, base_size=8, local_hub_step=hubs).collect()]
    assert len(found) == len(set(found)) and set(found) == brute(pairs, 3)
    assert depths == [] if held > 60 else depths
