"""Every method against closed forms and brute force, and the plan shapes that the methods rely on."""

from itertools import combinations, product
from math import comb

import pytest
from pyspark.sql import functions as F

from tricell import catalog, oracle
from tricell.costs import balance, formulas, profile
from tricell.costs.measured import spark_cost
from tricell.functions.colours import coefficients, colour
from tricell.functions.small_bias import SmallBiasSpace, multiply, modulus
from tricell.model import MemoryModel
from tricell.operators import base, baselines, canonical, cells, cliques, cone, consume, hubs, recursive, relational, steered, target
from tricell.plans import choose
from tricell.sources import generate, graphs
from tricell.streaming import incremental


def ranked_of(raw):
    return canonical.orient(canonical.canonical_edges(raw), keep_degrees=True)


def triples(df):
    rows = [tuple(sorted((r.a, r.b, r.c))) for r in df.collect()]
    assert len(rows) == len(set(rows)), "a triangle came twice"
    return set(rows)


def brute(pairs):
    near = {}
    for u, v in pairs:
        if u != v and u is not None and v is not None:
            near.setdefault(u, set()).add(v)
            near.setdefault(v, set()).add(u)
    return {t for t in combinations(sorted(near), 3) if t[1] in near[t[0]] and t[2] in near[t[0]] and t[2] in near[t[1]]}


@pytest.fixture(scope="module")
def messy(spark):
    """A random graph with two hubs, loops, repeats, reversals and nulls."""
    raw = [(r.u, r.v) for r in generate.random_pairs(spark, 40, 150, 3).collect()]
    raw += [(100, i) for i in range(40)] + [(i, 101) for i in range(40)] + [(100, 101), (5, 5), (101, 100), (None, 3), (3, None)]
    return spark.createDataFrame(raw, "u long, v long"), brute(raw)


@pytest.mark.parametrize("c", [1, 2, 3, 4, 8])
@pytest.mark.parametrize("kernel", ["join", "arrow"])
def test_cells_are_exact_for_every_memory(spark, messy, c, kernel):
    r = ranked_of(messy[0])
    assert triples(cells.enumerate_cells(r, MemoryModel.for_colours(r.count(), c), seed=c, kernel=kernel)) == messy[1]


@pytest.mark.parametrize("family", ["poly4", "poly2", "xxhash", "modulo", "constant", "wide"])
def test_the_answer_does_not_depend_on_the_colours(spark, messy, family):
    r = ranked_of(messy[0])
    assert triples(cells.enumerate_cells(r, MemoryModel.for_colours(r.count(), 4), family=family)) == messy[1]


def test_other_methods_agree(spark, messy):
    raw, expected = messy
    r = ranked_of(raw).cache()
    e = r.select("lo", "hi")
    mm = MemoryModel.for_colours(r.count(), 2)
    assert triples(baselines.naive_triangles(e)) == expected
    assert triples(baselines.sort_wedge_triangles(e, strict=True)) == expected
    assert triples(baselines.base_scan_triangles(e, mm)) == expected
    assert triples(base.triangles_by_base(e, e, mm, mode="keyed")) == expected
    assert triples(baselines.nested_loop_triangles(e)) == expected
    assert triples(baselines.brute_triangles(e)) == expected
    assert triples(choose.enumerate_planned(r, mm)) == expected
    assert triples(recursive.enumerate_recursive(r, base_size=8)) == expected
    assert triples(recursive.enumerate_recursive(r, base_size=8, local_hub_step=False)) == expected
    assert triples(recursive.level_cells(r, 2, 1)) == expected
    assert triples(recursive.enumerate_shared(r, base_size=8)) == expected
    deg = canonical.degrees(e)
    assert triples(steered.enumerate_steered(r, deg, MemoryModel.for_colours(r.count(), 4))) == expected


def test_vertex_and_target_methods(spark, messy):
    raw, expected = messy
    r = ranked_of(raw)
    for v in (100, 7):
        assert triples(cone.triangles_at(r, v)) == {t for t in expected if v in t}
    marked = hubs.mark_hubs(r, 30)
    assert triples(cone.triangles_at_set(marked)) == {t for t in expected if {100, 101} & set(t)}
    weak = cone.triangles_at_set(marked, exactly_once=False).count()
    assert weak == sum(len({100, 101} & set(t)) for t in expected)
    paint = lambda x: colour(F.col(x), 2, 1)
    painted = r.select("lo", "hi", paint("lo").alias("x_lo"), paint("hi").alias("x_hi"))
    found = set()
    for z in product((1, 2), repeat=3):
        part = triples(target.enumerate_target(painted, z))
        assert not found & part
        found |= part
    assert found == expected


@pytest.mark.parametrize(
    "make, count",
    [
        (lambda s: generate.clique(s, 12), comb(12, 3)), (lambda s: generate.wheel(s, 9), 9), (lambda s: generate.tripartite(s, 2, 3, 4), 24),
        (lambda s: generate.book(s, 6), 6), (lambda s: generate.three_hubs(s, 10), 31), (lambda s: generate.star(s, 10), 0), (lambda s: generate.clique(s, 2), 0), (lambda s: generate.clique(s, 3), 1),
    ],
)
def test_closed_forms(spark, make, count):
    r = ranked_of(make(spark))
    for c in (2, 8):
        assert cells.enumerate_cells(r, MemoryModel.for_colours(r.count(), c)).count() == count
    assert recursive.enumerate_recursive(r, base_size=4).count() == count


def test_empty_graph(spark):
    r = ranked_of(spark.createDataFrame([], "u long, v long"))
    assert cells.enumerate_cells(r, MemoryModel(4)).count() == 0
    assert recursive.enumerate_recursive(r).count() == 0
    assert base.triangles_by_base(r.select("lo", "hi"), r.select("lo", "hi"), MemoryModel(4)).count() == 0


def test_cliques_and_cycles(spark):
    e = canonical.orient(canonical.canonical_edges(generate.clique(spark, 8)))
    assert cliques.enumerate_cliques(e, 4, colours=2).count() == comb(8, 4)
    assert cliques.enumerate_cliques(e, 5, colours=2).count() == comb(8, 5)
    assert cliques.cliques_by_growth(e, 4).count() == comb(8, 4)
    assert cliques.four_cycles(e).count() == 3 * comb(8, 4)
    assert cliques.enumerate_pattern(e, cliques.DIAMOND, colours=2).count() == 6 * comb(8, 4)


def test_patterns_equal_brute_force(spark, messy):
    e = canonical.orient(canonical.canonical_edges(messy[0]))
    near = {}
    for r in e.collect():
        near.setdefault(r.lo, set()).add(r.hi)
        near.setdefault(r.hi, set()).add(r.lo)
    cycles = {(a, b, c, d) for a in near for b in near[a] if a < b for c in near[b] if a < c for d in near[c] & near[a] if b < d}
    diamonds = {(a, b, c, d) for a in near for b in near[a] if a < b for c, d in combinations(sorted(near[a] & near[b]), 2)}
    for pattern, wanted in ((cliques.FOUR_CYCLE, cycles), (cliques.DIAMOND, diamonds)):
        for c in (1, 3):
            got = [tuple(r) for r in cliques.enumerate_pattern(e, pattern, colours=c).collect()]
            assert len(got) == len(wanted) and set(got) == wanted


def test_regrouping_changes_no_bit(spark, messy):
    r = ranked_of(messy[0])
    deg = canonical.degrees(r.select("lo", "hi"))
    edges, space = steered.with_columns(r, deg, 0.5)
    found = [steered.choose_colouring(edges, space, 8, r.count(), 8, 0.5, regroup=g) for g in (True, False)]
    assert found[0].members == found[1].members and found[0].potentials == found[1].potentials


def test_shared_subproblems_equal_stored_ones(spark, messy):
    """The views of one copy of the edges hold what the stored levels hold."""
    r = ranked_of(messy[0]).cache()
    wanted = recursive.levels(r, 1, 2, prune=False)
    live, removed = spark.createDataFrame([(1, 1, 1)], "z0 int, z1 int, z2 int"), []
    for i in range(3):
        view = recursive.shared_view(r, live, removed, i, 1)
        key = [*recursive.Z, "lo", "hi", "x_lo", "x_hi"]
        assert sorted(map(tuple, view.select(key).collect())) == sorted(map(tuple, wanted[i].select(key).collect()))
        removed.append((i, recursive.local_hubs(view).select(*recursive.Z, "id")))
        live = recursive.child_triples(live)


def test_estimates_from_samples(spark, messy):
    r = ranked_of(messy[0])
    assert choose.sampled_estimate(r, 1.0) == len(messy[1])
    seen = [choose.sampled_estimate(r, 0.5, seed) for seed in range(6)]
    assert abs(sum(seen) / len(seen) - len(messy[1])) < 0.4 * len(messy[1])


def test_interval_join_of_late_and_early_rows(spark, tmp_path):
    """Two files of rows, in order of time, and rows beyond the watermark."""
    from tricell.streaming import windows

    schema = "k string, n long, ts timestamp"
    batches = [["('a', 1, '2024-01-01 00:00:00')", "('a', 2, '2024-01-01 00:00:50')", "('b', 3, '2024-01-01 00:00:10')"], ["('a', 4, '2024-01-01 00:01:30')", "('b', 5, '2024-01-01 00:30:00')"]]
    rows = [spark.sql(" union all ".join(f"select col1 as k, cast(col2 as long) as n, to_timestamp(col3) as ts from values {x}" for x in batch)) for batch in batches]
    wanted = {(x.left_n, x.right_n) for x in windows.interval_join(rows[0].union(rows[1]), rows[0].union(rows[1]), ["k"], "ts", 60).collect()}
    assert (1, 2) in wanted and (2, 4) in wanted and (1, 4) not in wanted and (3, 5) not in wanted
    side = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    for batch in rows:
        batch.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        joined = windows.interval_join(side(), side(), ["k"], "ts", 60, late="1 minute")
        joined.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/ck").trigger(availableNow=True).start().awaitTermination(120)
    got = [(x.left_n, x.right_n) for x in spark.read.parquet(f"{tmp_path}/out").collect()]
    assert len(got) == len(set(got)) and set(got) == wanted


def test_three_way_join(spark):
    rows = [(s, b, t) for s in range(3) for b in "xyz"[: s + 1] for t in (1.5, 2.5)] + [(0, "z", 1.5)]
    df = spark.createDataFrame(rows, "s long, b string, t double")
    got = relational.is_join_of_projections(df, ("s", "b", "t")).first()
    rst = [set((r[i], r[j]) for r in rows) for i, j in ((0, 1), (1, 2), (0, 2))]
    joined = {(s, b, t) for s, b in rst[0] for b2, t in rst[1] if b == b2 and (s, t) in rst[2]}
    assert (got.true_rows, got.joined_rows) == (len(set(rows)), len(joined))
    wide = relational.three_way_join(*relational.decompose(df, ("s", "b", "t")), ("s", "b", "t"), shares=(3, 2, 1), project=["s"])
    assert {r.s for r in wide.collect()} == {s for s, _, _ in joined}


def test_cells_shuffle_three_times_and_never_to_one_task(spark):
    r = ranked_of(generate.random_pairs(spark, 200, 1500)).cache()
    r.count()
    plan = cells.CellPlan.make(r.count(), MemoryModel.for_colours(r.count(), 4))
    df = cells.join_kernel(cells.coloured(r.select("lo", "hi"), plan), 4)
    text = df._jdf.queryExecution().sparkPlan().toString() + df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[-1]
    assert text.count("Exchange hashpartitioning(cell") == 3
    assert "SinglePartition" not in text


def test_four_wise_independence_of_the_small_field():
    p = 5
    for xs in combinations(range(p), 4):
        seen = set()
        for ks in product(range(p), repeat=4):
            seen.add(tuple((((ks[0] * x + ks[1]) * x + ks[2]) * x + ks[3]) % p for x in xs))
        assert len(seen) == p**4
    assert len(coefficients(1)) == 4 and coefficients(1) == coefficients(1) != coefficients(2)


def test_small_bias_of_four_bits():
    space = SmallBiasSpace(4, 2.0)
    vectors = [space.vector(j) for j in range(space.size)]
    columns = [space.column(x) for x in range(16)]
    assert all(multiply(multiply(x, x, modulus(4)), x, modulus(4)) == columns[x] >> 5 for x in range(16))
    for xs in combinations(range(16), 4):
        counts = {}
        for v in vectors:
            key = tuple((columns[x] & v).bit_count() & 1 for x in xs)
            counts[key] = counts.get(key, 0) + 1
        assert max(counts.values()) <= (1 + space.alpha) * len(vectors) / 16


def test_steering_keeps_its_guarantee_and_repeats(spark, messy):
    r = ranked_of(messy[0])
    n = r.count()
    mm = MemoryModel.for_colours(n, 4)
    deg = canonical.degrees(r.select("lo", "hi"))
    one, two = (steered.steered_classes(r, deg, mm)[2] for _ in range(2))
    assert one.members == two.members
    assert all(p <= c for p, c in zip(one.potentials, one.caps))


def test_mean_pair_mass_stays_under_its_bound(spark):
    r = ranked_of(generate.random_pairs(spark, 60, 500, 9)).cache()
    n = r.count()
    mm = MemoryModel.for_colours(n, 4)
    low = hubs.mark_hubs(r, hubs.least_hub_degree(n, mm.m)).where(~hubs.touches_hub()).select("lo", "hi")
    bound = balance.pair_mass_bound(canonical.degrees(low), n, 4, mm.m).first()
    seeds = [balance.pair_mass(cells.coloured(low, cells.CellPlan.make(n, mm, seed=s))).first().pair_mass for s in range(20)]
    assert sum(seeds) / 20 <= 1.1 * bound.expected_bound
    assert bound.expected_bound <= bound.edges_times_memory


def test_local_hubs_are_few_and_levels_grow_as_derived(spark):
    r = ranked_of(generate.random_pairs(spark, 60, 600, 4)).cache()
    levels = recursive.levels(r, 1, 2, local_hub_step=False, prune=False)
    n = r.count()
    assert [lv.count() for lv in levels] == [(3 * 2**i - 2) * n for i in range(3)]
    worst = recursive.local_hubs(levels[2]).groupBy("z0", "z1", "z2").count().agg(F.max("count")).first()[0]
    assert (worst or 0) <= 16


def test_measured_transfers_grow_with_the_colours(spark):
    r = ranked_of(generate.random_pairs(spark, 300, 9000, 8)).cache()
    n = r.count()
    cost = {}
    for c in (2, 4, 8):
        found, cost[c] = spark_cost(spark, lambda c=c: cells.enumerate_cells(r, MemoryModel(n), edges=n, colours=c, hub_step=False).count())
        assert found == baselines.naive_triangles(r.select("lo", "hi")).count()
        # three roles of c copies each, besides one row a task for the count
        assert 3 * c * n <= cost[c].shuffle_records <= 3 * c * n + cost[c].tasks
        assert cost[c].shuffle_bytes > 0 and cost[c].spilled_bytes == 0
    _, nothing = spark_cost(spark, lambda: None)
    assert nothing.tasks == 0 and spark.sparkContext.getLocalProperty("spark.jobGroup.id") is None


def test_moments_of_a_role_class_over_seeds(spark):
    r = ranked_of(generate.random_pairs(spark, 200, 3000, 6)).cache()
    for row in profile.role_moments_over_seeds(r, 2, tuple(range(1, 41))).collect():
        assert row.seeds == 40 and row.variance <= row.bound
        assert abs(row.mean_size - row.expected) <= 4 * (row.bound / 40) ** 0.5


def test_formulas():
    mm = MemoryModel(100, 4)
    assert formulas.replication(4) == 10
    assert formulas.gain(10_000, mm) == 10
    assert formulas.lower_bound_io(0, mm) == 0
    assert formulas.max_triangles(comb(10, 2)) >= comb(10, 3)
    assert formulas.IoLedger(mm).scan("x", 9).total() == 3
    assert mm.colours(100) == 1 and mm.colours(101) == 2 and mm.colours(1000, power_of_two=True) == 4


def test_consumers(spark):
    r = ranked_of(generate.clique(spark, 6))
    tri = baselines.naive_triangles(r.select("lo", "hi"))
    assert {x.triangles for x in consume.vertex_triangles(tri).collect()} == {comb(5, 2)}
    assert consume.transitivity(tri, canonical.degrees(r.select("lo", "hi"))).first().transitivity == 1
    assert {x.support for x in consume.edge_support(tri, r).collect()} == {4}
    assert consume.truss_round(tri, r, 6).count() == 15 and consume.truss_round(tri, r, 7).count() == 0


def test_stream_reports_each_triangle_when_its_last_edge_comes(spark, tmp_path):
    rows = canonical.canonical_edges(generate.random_pairs(spark, 15, 60, 2)).collect()
    for k in range(3):
        spark.createDataFrame(rows[k::3], "u long, v long").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    from tricell.sources.files import stream_edges

    seen = []
    query = incremental.run_incremental(stream_edges(spark, f"{tmp_path}/in"), f"{tmp_path}/store", f"{tmp_path}/ck", lambda df, n: seen.extend(tuple(r) for r in df.collect()))
    query.awaitTermination(120)
    assert len(seen) == len(set(seen)) and set(seen) == brute([(r.u, r.v) for r in rows])


@pytest.mark.parametrize("shift", [0, 1 << 62, -(1 << 62), 10**12, (1 << 31) - 20])
def test_ids_of_any_size(spark, messy, shift):
    """The same graph under other ids: negative, far apart, and on both sides of the small field."""
    raw, expected = messy
    moved = raw.select((F.col("u") + shift).alias("u"), (F.col("v") + shift).alias("v"))
    r = canonical.orient(canonical.canonical_edges(moved), keep_degrees=True).cache()
    wanted = {tuple(x + shift for x in t) for t in expected}
    mm = MemoryModel.for_colours(r.count(), 4)
    assert triples(cells.enumerate_cells(r, mm)) == wanted
    assert triples(recursive.enumerate_recursive(r, base_size=16)) == wanted
    assert triples(cells.enumerate_cells(r, mm, family="wide")) == wanted


def test_colours_of_wide_ids_are_balanced(spark):
    ids = spark.range(20_000).select((F.col("id") * 7_919_000_011 + (1 << 40)).alias("id"))
    n = [r.n for r in ids.groupBy(colour(F.col("id"), 4, 1).alias("k")).agg(F.count("*").alias("n")).collect()]
    assert len(n) == 4 and max(n) - min(n) < 600


def test_steering_scores_equal_a_plain_count(spark):
    """Pairs of edges in one new class, and those at one vertex, counted edge by edge."""
    from collections import Counter

    space = SmallBiasSpace(5, 0.5)
    edges = [(a, b) for a, b in combinations(range(24), 2) if (a * 7 + b * 5) % 3 == 0]
    x = {v: v % 2 + 1 for v in range(24)}
    df = spark.createDataFrame([(a, b, x[a], x[b], space.column(a), space.column(b)) for a, b in edges], "lo long, hi long, x_lo int, x_hi int, y_lo long, y_hi long")
    members = [0, 1, 5, 9, 40]
    got = {r.member: (int(r.total), int(r.adjacent)) for r in steered.scores(df, space, members).collect()}
    for j in members:
        bit = lambda v: (space.column(v) & space.vector(j)).bit_count() & 1  # noqa: E731, B023
        new = {v: 2 * x[v] - bit(v) for v in range(24)}
        classes, at = Counter(), Counter()
        for a, b in edges:
            k = (new[a], new[b])
            classes[k] += 1
            at[k, a] += 1
            at[k, b] += 1
        assert got[j] == (sum(comb(n, 2) for n in classes.values()), sum(comb(n, 2) for n in at.values()))


def test_field_columns_of_many_ids_equal_those_of_one():
    import numpy as np

    for bits in (1, 2, 5, 13, 31):
        space = SmallBiasSpace(bits, 0.5)
        ids = np.unique(np.random.default_rng(bits).integers(0, 1 << bits, 200))
        assert space.columns(ids).tolist() == [space.column(int(v)) for v in ids]


def test_many_batches_make_one_plan(spark, messy):
    raw, expected = messy
    e = canonical.orient(canonical.canonical_edges(raw))
    df = base.triangles_by_base(e, e, MemoryModel(4), alpha=1.0)
    assert triples(df) == expected
    assert "Union" not in df._jdf.queryExecution().optimizedPlan().toString()


def test_role_moments_of_many_edges_equal_the_sql(spark, duck):
    """Sizes whose squares pass 2^53, where one rounding of a power shows in the variance."""
    for n in (97_000_043, 97_000_235):
        sizes = [[(0, n, n, n)], [(z, n // 4 + 1009 * z, n // 4 - 917 * z + 1, n // 4 + z * z) for z in range(8)]]
        tables = [spark.createDataFrame(x, "z0 long, tip_mid long, tip_top long, base long") for x in sizes]
        got = profile.role_class_moments(tables, n)
        values = ", ".join(f"({i}, {r[1]}, {r[2]}, {r[3]})" for i, x in enumerate(sizes) for r in x)
        lv = f"lv as (select level, r0::hugeint as r0, r1::hugeint as r1, r2::hugeint as r2 from (values {values}) t(level, r0, r1, r2))"
        tail = catalog.oracle_sql()["role_class_moments"].split(") select level, round(", 1)[1].replace("(select count(*) from o)", str(n))
        want = duck.execute(f"with {lv} select level, round({tail}").fetchall()
        assert sorted(got) == sorted(want), n


def test_vectors_meet_in_blocks(spark, duck, monkeypatch, tmp_path):
    """Blocks smaller than the table, scores beside the threshold, repeats and nulls; the plan holds no join of all pairs."""
    monkeypatch.setattr(graphs, "VECTORS_A_BLOCK", 7)
    rows = [(k, [float((k * 7 + j * j * 3) % 11 - 4) for j in range(4)]) for k in range(30)]
    for k, cosine in enumerate((0.2999994, 0.2999995, 0.2999996, 0.3)):
        rows.append((100 + k, [cosine, (1 - cosine * cosine) ** 0.5, 0.0, 0.0]))
    rows += [(200, [1.0, 0.0, 0.0, 0.0]), (200, [1.0, 0.0, 0.0, 0.0]), (201, None), (None, [1.0, 0.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = graphs.vectors(spark, str(tmp_path))
    duck.execute(f"create or replace temp view embeddings as select * from read_parquet('{tmp_path}/embeddings.parquet/*.parquet')")
    want = duck.execute(f"with {oracle.PAIRS['vec']} select distinct u, v from p").fetchall()
    duck.execute("drop view temp.embeddings")
    found = {tuple(r) for r in got.collect()}
    assert found == set(want) and (103, 200) in found and (100, 200) not in found
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_cells_too_large_to_hash_are_dealt_in_parts(spark, sf_dir, monkeypatch):
    """Paths are not sorted: nothing but the inputs of the cells is."""
    r = catalog.ranked(spark, sf_dir, "copurchase")
    n = r.count()
    plan = cells.CellPlan.make(n, MemoryModel.for_colours(n, 2))
    classed = cells.coloured(r.select("lo", "hi"), plan)
    want = sorted(map(tuple, cells.join_kernel(classed, 2).collect()))
    monkeypatch.setattr(cells, "HASHED_EDGES", 64)
    assert cells.partitions_for(spark, n, 2) is None
    df = cells.join_kernel(classed, 2, edges=n)
    text = df._jdf.queryExecution().sparkPlan().toString()
    assert "ShuffledHashJoin" in text and text.count("SortMergeJoin") <= 1
    assert sorted(map(tuple, df.collect())) == want and want


def test_rejoined_projections_are_dealt_to_many_cells(spark):
    """Without a memory model too; all lay in one cell, so in one task."""
    table = spark.createDataFrame([(x, y, z) for x in range(6) for y in range(5) for z in range(4) if (x + y * z) % 3], "x long, y long, z long")
    xyz = {tuple(r) for r in table.collect()}
    parts = [{(t[i], t[j]) for t in xyz} for i, j in ((0, 1), (1, 2), (0, 2))]
    joined = [(x, y, z) for x, y in parts[0] for w, z in parts[1] if w == y and (x, z) in parts[2]]
    assert relational.is_join_of_projections(table, "xyz").first().asDict() == {"true_rows": len(xyz), "joined_rows": len(joined), "spurious_rows": len(joined) - len(xyz)}
    shares = relational.shares_for(spark, 7_000_000)
    assert shares[0] * shares[2] >= max(7, spark.sparkContext.defaultParallelism)
    again = relational.three_way_join(*relational.decompose(table, "xyz"), "xyz", shares=shares, hashed=True)
    assert "ShuffledHashJoin" in again._jdf.queryExecution().sparkPlan().toString()
    assert sorted(map(tuple, again.collect())) == sorted(joined)
