"""Cliques counted in blocks of colours against brute force, and what is shuffled for them."""

from __future__ import annotations

import random
from itertools import combinations
from math import comb

import pytest

from subcount import model
from subcount.operators import blocks, cliques, exact, experiments, measures, patterns, peel
from subcount.sources import edges as sources


def graph(n, p, seed=3):
    r = random.Random(seed)
    return [e for e in combinations(range(n), 2) if r.random() < p]


def frame(spark, pairs):
    return spark.createDataFrame([(7 * a - 3, 7 * b - 3) for a, b in pairs], "src long, dst long")


@pytest.mark.parametrize("n,p,c", [(30, 0.5, 4), (30, 0.5, 1), (24, 0.8, 3), (12, 1.0, 2), (6, 0.0, 4)])
def test_blocks_equal_brute_force(spark, n, p, c):
    pairs = graph(n, p)
    known = set(pairs)
    want = {k: [t for t in combinations(range(n), k) if all(x in known for x in combinations(t, 2))] for k in (3, 4)}
    e = frame(spark, pairs)
    assert [blocks.count(e, k, c=c).first()[0] for k in (3, 4)] == [len(want[k]) for k in (3, 4)]
    assert sorted(map(tuple, blocks.triangles(e, c=c).collect())) == [tuple(7 * x - 3 for x in t) for t in want[3]]
    assert cliques.count_ordered(e, 4, most=0).first()[0] == len(want[4])


@pytest.fixture
def no_broadcast(spark):
    """As on graphs whose tables pass the broadcast limit."""
    key = "spark.sql.autoBroadcastJoinThreshold"
    old = spark.conf.get(key)
    spark.conf.set(key, "-1")
    yield
    spark.conf.set(key, old)


def test_ordered_cliques_of_a_dense_graph_shuffle_no_wedges(spark, no_broadcast):
    e = frame(spark, graph(150, 1.0))
    for k in (3, 4):
        counted = cliques.count_ordered(e, k)
        assert counted.first()[0] == comb(150, k)
        assert measures.run_cost(counted)["shuffle_written"] < 500_000  # half a million wedges, 20 million cliques


def test_stats_of_a_dense_graph_shuffle_no_wedges(spark, monkeypatch, no_broadcast):
    monkeypatch.setitem(experiments.graphs.GRAPHS, "dense", lambda s, d: model.canonical(frame(s, graph(150, 1.0))))
    stats = experiments.graph_stats(spark, "", "dense")
    assert tuple(stats.first()) == ("dense", 150, comb(150, 2), comb(150, 3), 149)
    assert measures.run_cost(stats)["shuffle_written"] < 500_000


def test_theory_row_counts_triangles_in_blocks(spark, monkeypatch):
    from subcount.operators import exact
    from subcount.queries import graph as queries

    monkeypatch.setattr(exact, "close_wedges", lambda *a, **b: pytest.fail("wedges became rows"))
    for name in ("msr_theory_copurchase", "exp_scaling_tripartite"):
        assert queries.QUERIES[name](spark, "/root/testdata/sf0.001").count() >= 1


def test_rounds_hear_in_blocks_what_messages_tell(spark):
    """The trace equals the one of message rows in every round, on ids that are hashes and where peeling stalls; and
    its plan joins no arcs to arcs."""
    rng = random.Random(11)
    ids = [rng.randrange(-(1 << 62), 1 << 62) for _ in range(60)]
    e = sources.pairs(spark, [tuple(rng.choices(ids, k=2)) for _ in range(500)] + [tuple(rng.choices(ids[:12], k=2)) for _ in range(150)])
    for gamma in (peel.schedule("from_bound", 5), peel.schedule("constant", 9), peel.schedule("constant", 14), peel.schedule("plain")):
        t = peel.rounds(e, gamma)
        got = {r["round"]: (r["found2"], r["found4"], r["found6"]) for r in exact.duplicates_trace(e, gamma, t).collect()}
        assert got == {r.number: tuple(exact.class_totals(r).first()) for r in t.rounds}
    assert exact.count_by_duplicates(e, peel.schedule("from_bound", 5)).first()[0] == exact.count_by_rank(e).first()[0] > 0
    plan = exact.duplicates_trace(e, peel.schedule("from_bound", 5))._jdf.queryExecution().optimizedPlan().toString()
    assert "w#" not in plan and "MapInArrow" in plan


@pytest.mark.parametrize("name", ("triangle", "k4"))
def test_complete_patterns_make_no_wedge_rows(spark, name):
    e = frame(spark, graph(40, 0.4))
    got = patterns.count(e, name)
    assert got.columns == ["copies"] and got.first()[0] == patterns.brute(e, name).first()[0] > 0
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("c", (3, None))
def test_patterns_of_four_vertices_are_counted_in_blocks(spark, c):
    """Also on ids that are hashes, on a hub and without edges; the plan of the 4-cycles joins nothing to make wedges."""
    hub = [(0, x) for x in range(1, 40)] + graph(40, 0.15)
    hashes = spark.createDataFrame([(hash((a, 1)), hash((b, 1))) for a, b in graph(25, 0.4)], "src long, dst long")
    for e in (frame(spark, graph(25, 0.5)), model.canonical(frame(spark, hub)), model.canonical(hashes), frame(spark, [])):
        got = blocks.fours(e, c).first().asDict()
        assert got == {name: patterns.brute(e, name).first()[0] for name in blocks.FOURS}
    assert "Join" not in patterns.count(e, "cycle4")._jdf.queryExecution().optimizedPlan().toString()


def test_rounds_are_traced_without_tables_of_a_round(spark, monkeypatch):
    """In memory, and in written tables that go with their round, as peel.rounds tells them; also where peeling stalls."""
    from subcount.operators import orient

    e = model.canonical(sources.pairs(spark, [(a * a % 61, b) for a, b in graph(60, 0.2)]))
    kinds = [("from_bound", 3), ("constant", 9), ("constant", 4)]
    want = [[(r.number, r.gamma, r.n, r.edges, r.peeled, r.messages) for r in peel.rounds(e, peel.schedule(*s)).rounds] for s in kinds]
    assert orient.traces(e, kinds, most=0) == want
    monkeypatch.setattr(peel, "materialize", lambda *a: pytest.fail("a round became a table"))
    assert orient.traces(e, kinds) == want and any(want)


def test_rows_near_in_time_are_dealt_once(spark):
    """At the ends of buckets, before time 0 and with repeats, and the plan joins nothing."""
    from subcount import graphs

    r = random.Random(5)
    rows = [(r.randrange(3), r.randrange(40), r.randrange(-200, 200)) for _ in range(300)] + [(0, 99, t) for t in (-45, -44, -1, 0, 43, 44, 54)] * 2
    want = {(min(x, y), max(x, y)) for k, x, t in rows for l, y, u in rows if k == l and x != y and abs(t - u) <= 10}
    near = graphs.near_in_time(spark.createDataFrame(rows, "k long, who long, at long"), "k", "who", "at", 10)
    assert sorted(map(tuple, near.collect())) == sorted(want)
    assert "Join" not in near._jdf.queryExecution().optimizedPlan().toString()


def test_blocks_are_dealt_in_waves_from_a_packed_table(spark, monkeypatch):
    """Repeats, loops and null ends go as pairs are packed, and every block is in one wave whose files go with it."""
    pairs = graph(40, 0.4)
    dirty = [(7 * b - 3, 7 * a - 3) for a, b in pairs] * 2 + [(7 * a - 3, 7 * b - 3) for a, b in pairs[::3]] + [(4, 4), (None, 4)]
    cells = blocks.stored(spark.createDataFrame(dirty, "src long, dst long"))
    e = frame(spark, pairs)
    assert blocks.edges_of(cells) == len(pairs)
    assert sorted(map(tuple, blocks.degrees_of(cells).collect())) == sorted(map(tuple, model.degrees(e).collect()))
    want = [blocks.count(e, k).first()[0] for k in (3, 4)]
    waves, dealt = [], blocks._in_blocks
    monkeypatch.setattr(blocks, "_in_blocks", lambda *a: waves.append(a[-1]) or dealt(*a))
    monkeypatch.setattr(blocks, "WAVE_EDGES", len(pairs))
    assert [blocks.count_stored(cells, k).first()[0] for k in (3, 4)] == want
    assert len(waves) == sum(blocks.copies(blocks.LEAST_COLOURS, k) for k in (3, 4))


def test_an_orders_lines_are_dealt_once(spark, tmp_path):
    from subcount import graphs

    rows = [(1, 5), (1, 3), (1, 3), (1, None), (2, 9), (None, 1), (None, 2), (3, 7), (3, 5), (3, 3)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long").write.parquet(str(tmp_path / "lineitem.parquet"))
    e = graphs.copurchase(spark, str(tmp_path))
    assert sorted(map(tuple, e.collect())) == [(3, 5), (3, 7), (5, 7)]
    assert "Join" not in e._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("k", (1, 1 << 45))
def test_extended_edges_make_no_wedge_rows(spark, k):
    """Triangles by (degree, id), also on ids that are negative or long."""
    pairs = [(k * (a - 9), k * (b - 9)) if k > 1 else (a, b) for a, b in graph(30, 0.3) + [(0, x) for x in range(1, 30)]]
    e = model.canonical(spark.createDataFrame(pairs, "src long, dst long"))
    known = {frozenset(r) for r in e.collect()}
    deg = {v: sum(v in x for x in known) for x in known for v in x}
    want = [tuple(sorted(t, key=lambda v: (deg[v], v))) for t in combinations(sorted(deg), 3) if all(frozenset(x) in known for x in combinations(t, 2))]
    t = blocks.extended(e.unionAll(e))
    assert sorted(map(tuple, t.collect())) == sorted(want) and want
    if k == 1:
        assert "Join" not in t._jdf.queryExecution().optimizedPlan().toString()


def test_cliques_of_four_are_triangles_in_links(spark, monkeypatch):
    pairs = graph(40, 0.5)
    known = set(pairs)
    monkeypatch.setattr(blocks, "LINK_TRIANGLES", 300)
    t = blocks.count4_by_links(blocks.stored(frame(spark, pairs)))
    assert t.first()[0] == sum(all(x in known for x in combinations(t, 2)) for t in combinations(range(40), 4)) > 0
    assert "Join" not in t._jdf.queryExecution().optimizedPlan().toString()
    assert blocks.count4_by_links(blocks.stored(frame(spark, []))).first()[0] == 0


@pytest.mark.parametrize("hash_", ("kwise", "mixed"))
def test_samples_are_sent_packed(spark, monkeypatch, hash_):
    """As memberships joined to both ends tell them, over more than one slice of samples, with overflows."""
    from subcount.operators import approx

    e = spark.createDataFrame(graph(60, 0.4), "src long, dst long")
    p = approx.for_graph(e, mode="explicit", p=0.3, machines=90, k=6, space=int(0.09 * e.count()) + 12)
    rows = approx.assign(e, p, 2, hash_=hash_)
    fit = rows.join(approx.sizes(rows, p, 2).where("kept").select("rep", "i"), ["rep", "i"], "left_semi")
    want = sorted(map(tuple, approx.scaled(rows, approx.triangles_within(fit), p, 2, 3).collect()))
    monkeypatch.setattr(approx, "SLICE", 128)
    monkeypatch.setattr(approx, "assign", lambda *a, **b: pytest.fail("sent edges became rows"))
    assert sorted(map(tuple, approx.estimates(e, p, 2, hash_=hash_).collect())) == want and want[0][3] > 0


def test_polynomials_by_halves_equal_division():
    import numpy as np

    from subcount.operators import hashing

    x, c = np.array([0, 1, 2, hashing.P31 - 1, 12345678]), [hashing.P31 - 1, 7, hashing.P31 - 1, 0, 99]
    want = [sum(k * int(v) ** (len(c) - 1 - i) for i, k in enumerate(c)) % hashing.P31 for v in x]
    assert hashing.kwise_values(x, c, hashing.P31).tolist() == want


def test_vectors_are_dealt_once(spark):
    """No copy of a vector for each block: what is shuffled does not grow with the number of blocks."""
    from subcount import graphs

    plan = graphs.vecsim_pairs(spark, "/root/testdata/sf0.001", block=16)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate explode" not in plan and "Join Cross" in plan or "Join Inner" in plan


def test_repeated_long_values_are_packed_by_their_places():
    import numpy as np

    rng = np.random.default_rng(1)
    code = np.sort((rng.integers(300, 400, 600) << blocks.ID_BITS) | rng.choice(90_000, 600, replace=False))
    p, q = np.nonzero(np.triu(rng.random((600, 600)) < 0.2, 1))
    for x in (code[p], code[q], -code[q], p, rng.integers(-(2**62), 2**62, 5000), code[:3], np.empty(0, np.int64)):
        assert (blocks._swell(blocks._squeeze(x), len(x)) == x).all()
    assert len(blocks._squeeze(code[q])) < 1.2 * len(q) < len(blocks._squeezed(code[q])) / 2


def test_a_blocks_rows_are_sent_as_they_come(spark):
    """A worker does not hold all that its block gives."""
    import numpy as np
    import pyarrow as pa

    schema = pa.schema([("x", pa.int64()), ("mb", pa.int64())])

    def work(block):
        rss = lambda: int(open("/proc/self/statm").read().split()[1]) * 4096 >> 20
        first = rss()
        for _ in range(30):
            yield pa.table({"x": np.arange(1 << 20), "mb": np.full(1 << 20, rss() - first)}, schema=schema)

    rows = blocks._in_blocks(blocks.packed(frame(spark, [(1, 2), (2, 3), (1, 3)]), 1), 3, 1, work, "x long, mb long", schema)
    assert tuple(rows.selectExpr("count(*)", "max(mb) < 250").first()) == (30 << 20, True)
