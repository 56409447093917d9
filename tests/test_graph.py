"""Worked examples, agreement of the methods, invariants and plans."""

from __future__ import annotations

import random
from itertools import combinations
from math import comb

import pytest
from pyspark.sql import functions as F

from subcount import graphs, model
from subcount.operators import approx, baselines, cliques, exact, hashing, measures, orient, patterns, peel, primitives
from subcount.plans import planner
from subcount.sources import edges as sources
from subcount.streaming.edges import new_triangles

SF = "/root/testdata/sf0.001"


def frame(spark, pairs):
    return model.canonical(spark.createDataFrame(list(pairs), "src long, dst long")).coalesce(1).cache()


def brute(pairs):
    e = {frozenset(p) for p in pairs}
    v = sorted({x for p in pairs for x in p})
    return sum(all(frozenset(q) in e for q in combinations(t, 2)) for t in combinations(v, 3))


@pytest.fixture(scope="module")
def rand(spark):
    r = random.Random(5)
    pairs = {tuple(sorted(r.sample(range(24), 2))) for _ in range(90)}
    return frame(spark, pairs), brute(pairs), pairs


def test_dirty_rows(spark):
    d = spark.createDataFrame([(1, 2), (2, 1), (1, 1), (None, 3), (2, 3)], "src long, dst long")
    assert sorted(map(tuple, model.canonical(d).collect())) == [(1, 2), (2, 3)]
    assert tuple(model.dirt(d).first()) == (1, 1, 1)


@pytest.mark.parametrize("name,want", [("diamond", 2), ("bowtie", 2), ("k5", 10), ("empty", 0)])
def test_small_graphs(spark, name, want):
    pairs = {"diamond": [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)], "bowtie": [(0, 1), (0, 2), (1, 2), (0, 3), (0, 4), (3, 4)], "k5": list(combinations(range(5), 2)), "empty": []}[name]
    e = frame(spark, pairs)
    assert exact.count_by_rank(e).first()[0] == want
    assert exact.count_by_duplicates(e, peel.schedule("plain")).first()["triangles"] == want


def test_exact_methods_agree(rand):
    e, want, _ = rand
    t = peel.rounds(e, peel.schedule("from_bound", 5))
    raw = exact.count_by_duplicates(e, None, traced=t).first()
    assert raw["triangles"] == want and 2 * want <= raw["raw"] <= 6 * want
    for r in exact.duplicates_trace(e, None, t).collect():
        assert r["found2"] % 2 == r["found4"] % 4 == r["found6"] % 6 == 0
        assert r["messages"] <= 2 * r["edges"] * r["gamma"]
    for f in (exact.count_by_rank, baselines.brute, baselines.two_round, baselines.one_round, baselines.vertex_sweep, baselines.edge_intersection):
        assert f(e).first()[0] == want
    assert exact.count_by_edge_class(e, None, t).first()[0] == want
    assert baselines.folklore(e, 6).first()[0] == want
    assert planner.check(e)


def test_triangle_classes(spark):
    k = lambda base, others: [(base + i, x) for i in range(3) for x in others]
    tri = [(0, 1), (0, 2), (1, 2)]
    hub = lambda v: [(v, 100 + 10 * v + j) for j in range(5)]
    assert k(0, [])[:0] == []
    for hubs, want in (((), (0, 0, 6)), ((2,), (0, 4, 0)), ((1, 2), (2, 0, 0))):
        e = frame(spark, tri + [p for h in hubs for p in hub(h)])
        t = peel.rounds(e, peel.schedule("constant", 2))
        first = exact.class_totals(t.rounds[0]).first()
        assert tuple(first) == want


def test_constant_threshold_stalls(spark):
    r = baselines.peel_constant(frame(spark, combinations(range(5), 2)), 3).first()
    assert r["stalled"] and r["left_vertices"] == 5


def test_cliques(rand, spark):
    e, _, pairs = rand
    have = {frozenset(p) for p in pairs}
    for k in (3, 4):
        want = sum(all(frozenset(q) in have for q in combinations(t, 2)) for t in combinations(range(24), k))
        assert cliques.count_ordered(e, k).first()[0] == cliques.count_lifted(e, k).first()[0] == cliques.count_local(e, k).first()[0] == want
    k7 = frame(spark, combinations(range(7), 2))
    assert cliques.count_ordered(k7, 5).first()[0] == cliques.count_lifted(k7, 5).first()[0] == comb(7, 5)


@pytest.mark.parametrize("name", ["claw", "paw", "cycle4", "diamond", "butterfly", "k23", "banner"])
def test_patterns_match_brute_force(rand, name):
    e, *_ = rand
    assert patterns.count(e, name).first()[0] == patterns.brute(e, name).first()[0]


def test_catalogue_of_orientations():
    fixed = {"cycle4": (8, 3), "diamond": (4, 6), "gem": (2, 27), "house": (2, 21), "k5": (120, 1), "banner": (2, 18)}
    for name, (aut, classes) in fixed.items():
        assert (patterns.NAMED[name].automorphisms(), len(patterns.orientations(patterns.NAMED[name]))) == (aut, classes)
    assert len(patterns.NAMED) == 30


def test_estimator(rand, spark):
    e, want, _ = rand
    one = approx.plan(24, 90, mode="explicit", p=1.0, machines=1)
    assert approx.estimates(e, one).first()["estimate"] == want
    tiny = approx.Plan(24, 90, 0, 1.0, 2, 6, 0.5, "explicit")
    assert approx.estimates(e, tiny).first()["estimate"] is None
    p = approx.plan(24, 90, mode="explicit", p=0.5, machines=10)
    got = [sorted(map(tuple, approx.assign(e, p, how=h).collect())) for h in ("lists", "inline", "pairs")]
    assert got[0] == got[1] == got[2]
    runs = [r["estimate"] for r in approx.estimates(e, p, 20).collect()]
    assert abs(sum(runs) / len(runs) - want) < 0.5 * want
    with pytest.raises(ValueError):
        approx.plan(5, 0)


def test_hash_is_pairwise_independent_on_a_small_field():
    prime, seen = 7, {}
    for a in range(prime):
        for b in range(prime):
            key = ((a * 1 + b) % prime, (a * 2 + b) % prime)
            seen[key] = seen.get(key, 0) + 1
    assert set(seen.values()) == {1} and len(seen) == prime**2
    assert hashing.coefficients(4, 1, 0) != hashing.coefficients(4, 1, 1)


def test_primitives(spark):
    lines = spark.createDataFrame([(x,) for x in "abacabad"], "x string")
    want = {"a": 4, "b": 2, "c": 1, "d": 1}
    assert dict(map(tuple, primitives.count_repeats(lines, ["x"]).collect())) == want
    assert dict(map(tuple, primitives.count_repeats_tree(lines, "x", 4, 2).collect())) == want
    q = spark.createDataFrame([(1, 1), (1, 1), (2, 3)], "a long, b long")
    c = spark.createDataFrame([(1, 1), (1, 1), (5, 5)], "a long, b long")
    for how in ("join", "sort"):
        assert sorted(r["is_member"] for r in primitives.member(q, c, ["a", "b"], how).collect()) == [False, True, True]
    assert primitives.replicate(q, 5, 2).count() == 15


def test_orientation_and_degeneracy(spark, rand):
    assert orient.degeneracy(frame(spark, combinations(range(6), 2))).first()[0] == 5
    assert orient.degeneracy(sources.generate(spark, "grid", 5)).first()[0] == 2
    e, *_ = rand
    s = orient.sparsity(e).first()
    assert s["outdegree_by_core"] <= s["degeneracy"] and s["arboricity_low"] <= s["degeneracy"]


def test_incremental_equals_batch(spark, rand):
    e, want, pairs = rand
    pairs = sorted(pairs)
    old, new = frame(spark, pairs[:50]), frame(spark, pairs[50:])
    assert exact.count_by_rank(old).first()[0] + new_triangles(old, new).first()[0] == want


def test_plans_have_no_cross_join_and_push_down(spark):
    e = graphs.tripartite(spark, SF)
    assert measures.plan_stats(exact.count_by_rank(e))["nested_loops"] == 0
    text = graphs.table(spark, SF, "lineitem").where("l_quantity > 45").select("l_partkey")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in text


def test_flagship(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).first()[0] == 50463


def test_waves_in_memory_equal_written_ones(spark, monkeypatch):
    rng = random.Random(3)
    e = sources.pairs(spark, [(rng.randrange(60) * 10**12, rng.randrange(60) * 10**12 - 5) for _ in range(300)] + [(1, 2), (2, 3), (3, 4), (9, 8)])
    monkeypatch.setattr(orient, "LOCAL_ARCS", 0)
    written, k = orient.waves(e)
    for most in (200, 10**6):  # handed over on the way, and at once
        monkeypatch.setattr(orient, "LOCAL_ARCS", most)
        got, core = orient.waves(e)
        assert core == k and sorted(map(tuple, got.collect())) == sorted(map(tuple, written.collect()))
    assert orient.degeneracy(sources.pairs(spark, [(1, 1)])).first()[0] == 0


def test_long_bands_are_not_peeled_by_a_table_a_wave(spark, monkeypatch):
    """A band of more than a million arcs loses two vertices a wave; its tables are few all the same."""
    real, written = orient.materialize, []

    def counted(df):
        written.append(df)
        if len(written) > 4:
            raise AssertionError("a table a wave")
        return real(df)

    e = real(spark.range(70_000).select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id") + 1, F.col("id") + 8)).alias("dst")))
    monkeypatch.setattr(orient, "materialize", counted)
    assert orient.degeneracy(e).first()[0] == 8


@pytest.mark.parametrize("shift, step", ((0, 1), (-(1 << 44), 1 << 40)))
def test_degeneracy_of_large_graphs_without_a_table_for_each_wave(spark, monkeypatch, shift, step):
    """By bounds of the core numbers in several parts, to the end or until the rest fits one task; also where there are too many vertices."""
    from subcount.operators import cores
    from subcount.storage import materialize

    rng = random.Random(5)
    mixed = [(rng.randrange(70), rng.randrange(70)) for _ in range(400)]
    cliques = [(200 + a, 200 + b) for a, b in combinations(range(12), 2)] + [(211 + x, 212 + x) for x in range(20)]
    pairs = cliques if shift else mixed
    e = materialize(model.canonical(frame(spark, [(shift + step * a, shift + step * b) for a, b in pairs])))
    m, want = e.count(), orient.waves(e)[1]
    with monkeypatch.context() as patch:
        patch.setattr(orient, "waves", lambda *a: pytest.fail("a wave at a time"))
        patch.setattr(cores, "PART_ARCS", m // 2)
        patch.setattr(cores, "CHUNK", 16)
        for most, sweeps, wait in ((0, 8, 8), (m, 1, 0), (2 * m - 1, 1, 8)):
            patch.setattr(orient, "LOCAL_ARCS", most)
            patch.setattr(cores, "SWEEPS", sweeps)
            patch.setattr(cores, "WAIT", wait)
            assert orient.degeneracy(e).first()[0] == want
    monkeypatch.setattr(cores, "MOST_VERTICES", 3)
    assert cores.degeneracy(e, m, m, None) is None
