"""Queries do the whole job at sizes and shapes other than those of the SQL comparison."""

from __future__ import annotations

import math
import random
from itertools import combinations
from math import comb

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from subcount import graphs, model
from subcount.operators import approx, baselines, cliques, exact, hashing, orient, peel
from subcount.plans import planner

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def queries():
    return __spark_entry__.queries()


def sample_sizes(vertices, p, rep):
    """Vertices of each machine's sample, hashed in plain Python."""
    c, out = hashing.coefficients(p.k, p.seed, rep, p.prime), []
    for i in range(p.machines):
        n = 0
        for v in vertices:
            x, h = v * p.machines + i, 0
            for a in c:
                h = (h * x + a) % p.prime
            n += h < p.threshold
        out.append(n)
    return out


def test_copurchase_estimates_on_a_larger_graph(spark, queries, tmp_path):
    """One order of 800 parts, a complete graph: a sample expects 3196 edges, over the space 1200 of sf0.01."""
    spark.createDataFrame([(1, v, 1) for v in range(1, 801)], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    e = model.canonical(spark.createDataFrame(list(combinations(range(1, 801), 2)), "src long, dst long")).cache()
    p = approx.for_graph(e, mode="explicit", p=0.1, machines=20, k=6)
    assert (p.n, p.m) == (800, comb(800, 2)) and p.p**2 * p.m < p.space < p.m
    rows = {r["rep"]: r for r in queries["approx_overflow_copurchase"](spark, str(tmp_path)).collect()}
    runs = []
    for rep in range(4):
        fit = [n for n in sample_sizes(range(1, 801), p, rep) if comb(n, 2) <= p.space]
        hits = sum(comb(n, 3) for n in fit)
        runs.append(hits / (0.1**3 * len(fit)))
        assert rows[rep]["kept"] == len(fit) > 0 and rows[rep]["kept"] + rows[rep]["overflowed"] == 20
        assert rows[rep]["hits"] == hits and rows[rep]["estimate"] == pytest.approx(runs[-1], abs=1e-3)
    assert queries["approx_once_copurchase"](spark, str(tmp_path)).first()["estimate"] == pytest.approx(runs[0], abs=1e-3)
    assert queries["approx_median_copurchase"](spark, str(tmp_path)).first()[0] == pytest.approx(sorted(runs)[1], abs=1e-3)
    assert queries["approx_mom_copurchase"](spark, str(tmp_path)).first()[0] is not None
    load = queries["approx_load_copurchase"](spark, str(tmp_path)).first()
    assert load["overflowed"] == rows[0]["overflowed"]
    sent = queries["msr_sent_copurchase"](spark, str(tmp_path)).first()
    assert sent["over_fair_share"] == pytest.approx(sent["mean"] / (p.space * 20 / p.m), abs=1e-5)


def test_udtf_pairs_of_all_orders(spark, queries):
    orders = {}
    for k, p in graphs.table(spark, SF, "lineitem").select("l_orderkey", "l_partkey").collect():
        orders.setdefault(k, set()).add(p)
    want = sorted((k, *pair) for k, ps in orders.items() for pair in combinations(sorted(ps), 2))
    assert sorted(map(tuple, queries["udtf_pairs"](spark, SF).collect())) == want and want[-1][0] > 200


def test_replicate_blocks_of_all_days(spark, queries):
    days = {}
    for key, at in graphs.table(spark, SF, "orders").select("o_orderkey", "o_orderdate").collect():
        days.setdefault(at.date(), []).append(key)
    keys = [k for ks in days.values() for k in ks]
    assert sorted(map(tuple, queries["replicate_blocks"](spark, SF).collect())) == [(c, len(days), len(keys), sum(keys)) for c in range(10)]


def band(spark, n, reach):
    return model.canonical(spark.createDataFrame([(i, j) for i in range(n) for j in range(i + 1, min(n, i + reach + 1))], "src long, dst long")).coalesce(1).cache()


def test_local_cliques_when_the_cap_peels_few_vertices_a_round(spark):
    """Inner degree 6 at cap 4: four vertices a round, 500 rounds at a fixed cap."""
    n = 2000
    assert cliques.count_local(band(spark, n, 3), 3, c=0.1).first()[0] == (n - 2) + 2 * (n - 3)


def test_a_cut_peeling_is_an_error(spark):
    e = band(spark, 60, 3)
    with pytest.raises(RuntimeError):
        peel.rounds(e, peel.schedule("constant", 4), max_rounds=3)
    assert sum(r.peeled for r in peel.rounds(e, peel.schedule("constant", 4)).rounds) >= 57


def test_workloads_run_on_all_listed_graphs(spark, queries):
    """custpart and geo have no triangle, benchhit no edge at this size."""
    rows = {r["graph"]: r for r in queries["exp_correction"](spark, SF).collect()}
    assert set(rows) == set(graphs.GRAPHS) and rows["tripartite"]["triangles"] == 50463
    assert rows["geo"]["ratio"] is None and rows["cosupply"]["ratio"] == 6
    assert {r["graph"]: r["left_vertices"] for r in queries["exp_stalls"](spark, SF).collect()}.keys() == set(graphs.GRAPHS)
    assert all(queries[f"exp_patterns_{g}"] and queries[f"degeneracy_value_{g}"] for g in ("trade", "copart30", "custpart"))
    assert all(f"{q}_{g}" in queries for q in ("approx_overflow", "approx_load", "msr_sent") for g in ("tripartite", "cosupply"))


def test_ids_that_were_equal_modulo_the_machines_are_sampled_apart(spark):
    """Ids a multiple of the old modulus apart once shared every sample: a triangle of them was estimated at 110."""
    step = hashing.P31 // 2000
    e = model.canonical(spark.createDataFrame([(5, 5 + step), (5, 5 + 2 * step), (5 + step, 5 + 2 * step)], "src long, dst long"))
    p = approx.for_graph(e, mode="explicit", p=0.1, machines=2000, k=6, space=10)
    assert p.prime == hashing.P61
    runs = [r["estimate"] for r in approx.estimates(e, p, 40).collect()]
    assert abs(sum(runs) / len(runs) - 1) < 0.6 and max(runs) < 8


def test_ids_must_be_numbers_that_fit(spark):
    e = model.canonical(spark.createDataFrame([(-3, 4), (4, 9), (-3, 9)], "src long, dst long"))
    with pytest.raises(ValueError):
        approx.for_graph(e, mode="explicit", p=0.5, machines=4)
    small = approx.plan(3, 3, mode="explicit", p=0.5, machines=4)
    for how in ("lists", "inline"):
        with pytest.raises(Exception, match="vertex id"):
            approx.assign(e, small, how=how).collect()
    n = model.renumbered(e)
    assert sorted(map(tuple, n.collect())) == [(0, 1), (0, 2), (1, 2)]
    assert approx.estimates(n, approx.for_graph(n, mode="explicit", p=1.0, machines=3)).first()["estimate"] == 1
    with pytest.raises(ValueError):
        hashing.field(1 << 62)


def test_k_wise_values_agree_in_both_fields(spark):
    xs = [0, 1, 7, 10**6, hashing.P31 - 1]
    for prime in (hashing.P31, hashing.P61):
        for k in (3, 20):
            c = hashing.coefficients(k, 5, 0, prime)
            plain = []
            for x in xs:
                h = 0
                for a in c:
                    h = (h * x + a) % prime
                plain.append(h)
            assert hashing.kwise_values(np.array(xs), c, prime).tolist() == plain
            if prime == hashing.P31 or k == 3:
                cols = spark.createDataFrame([(x,) for x in xs], "x long").coalesce(1).select(hashing.kwise(F.col("x"), c, prime).alias("h"))
                assert [r["h"] for r in cols.collect()] == plain


def test_pairs_of_vertices_and_machines_collide_as_chance_has_it():
    """Over random polynomials two keys fall under the threshold together with the product of their shares."""
    keys, p, both, one = np.array([3 * 7 + 1, 3 * 7 + 2, 90 * 7 + 1]), 0.3, np.zeros(3), np.zeros(3)
    for rep in range(4000):
        hit = hashing.kwise_values(keys, hashing.coefficients(4, 9, rep), hashing.P31) < hashing.threshold(p)
        one += hit
        both += [hit[0] & hit[1], hit[0] & hit[2], hit[1] & hit[2]]
    assert np.allclose(one / 4000, p, atol=0.03) and np.allclose(both / 4000, p * p, atol=0.02)


def test_estimates_on_text_keys_are_unbiased(spark):
    e = graphs.numbered(spark, SF, "lexical").cache()
    truth = exact.count_by_rank(e).first()[0]
    for kind in ("kwise", "mixed"):
        p = approx.for_graph(e, mode="explicit", p=0.5, machines=20, k=4, space=10**6)
        runs = [r["estimate"] for r in approx.estimates(e, p, 6, hash_=kind).collect()]
        assert abs(sum(runs) / len(runs) - truth) < 0.15 * truth


def test_skips_draw_each_machine_with_the_probability():
    seen = np.zeros(50)
    for v in range(3000):
        got = hashing.skips(v, 0.2, 50, 3, 0)
        assert len(set(got.tolist())) == len(got)
        seen[got] += 1
    assert np.allclose(seen / 3000, 0.2, atol=0.04) and hashing.skips(7, 0.2, 50, 3, 0).tolist() == hashing.skips(7, 0.2, 50, 3, 0).tolist()


def test_replica_policies():
    lemma = approx.plan(100, 1000, space=100, mode="explicit", p=0.5, eps=0.5, vertices=4)
    assert lemma.machines == math.ceil(20 / (0.25 * 0.5**3))
    budget = approx.plan(100, 1000, space=100, mode="explicit", p=0.5, eps=0.5, vertices=4, replicas="budget")
    assert budget.machines == math.ceil(int(2000 * math.log(1000)) / 100)
    assert "lemma" in approx.plan(100, 1000, vertices=5).verdict and approx.repetitions(25) == 322


def test_factors_by_plain_counting(spark):
    """The workload's estimate on one graph, with samples hashed and triangles counted in plain Python."""
    e = graphs.numbered(spark, SF, "sharedline")
    pairs = sorted(map(tuple, e.collect()))
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
    p = approx.for_graph(e, delta=0.5)
    vertices, runs = {v for x in pairs for v in x}, []
    for rep in range(6):
        c = hashing.coefficients(p.k, p.seed, rep, p.prime)
        hits, kept = 0, 0
        ids = np.array(sorted(vertices))
        for i in range(p.machines):
            mine = set(ids[hashing.kwise_values(ids * p.machines + i, c, p.prime) < p.threshold].tolist())
            sent = [(a, b) for a, b in pairs if a in mine and b in mine]
            if len(sent) <= p.space:
                kept += 1
                hits += sum(len({x for x in near.get(a, ()) if x in mine} & {x for x in near.get(b, ()) if x in mine}) for a, b in sent)
        runs.append(hits / (p.p**3 * kept))
    means = sorted((runs[g] + runs[g + 3]) / 2 for g in range(3))
    from subcount.operators import experiments

    rows = {r["method"]: r for r in experiments.factors(spark, SF, ("sharedline",), 0.5).collect()}
    assert rows["overlapping samples"]["estimate"] == pytest.approx(means[1], abs=1e-2)


def test_frequent_lines_take_part(spark, tmp_path):
    """200 documents with one line: each is linked with its eight successors, over runs of ids of any size."""
    line, rare = "this line stands in every document", "this one stands in three of them"
    rows = [(3 * i, "\n".join([line] + [rare] * (i % 70 == 0))) for i in range(200)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    want = {(3 * i, 3 * j) for i in range(200) for j in range(i + 1, min(200, i + 9))} | {(0, 210), (0, 420), (210, 420)}
    for run in (1 << 16, 7):
        assert set(map(tuple, graphs.sharedline(spark, str(tmp_path), run=run).collect())) == want


def test_near_vectors_in_blocks(spark):
    rows = np.array([r["embedding"] for r in graphs.table(spark, SF, "embeddings").orderBy("vec_id").collect()], float)
    rows /= np.sqrt((rows * rows).sum(1, keepdims=True))
    want = {(int(a), int(b)) for a, b in zip(*np.nonzero(np.triu(rows @ rows.T >= 0.3, 1)))}
    ids = [r["vec_id"] for r in graphs.table(spark, SF, "embeddings").select("vec_id").orderBy("vec_id").collect()]
    for block in (4096, 100):
        assert set(map(tuple, graphs.vecsim(spark, SF, block=block).collect())) == {(ids[a], ids[b]) for a, b in want}


def test_levels_of_a_threshold_that_stalls(spark):
    e = band(spark, 40, 3)
    levels = planner.levels(e, peel.schedule("constant", 2), small=5)
    assert levels.count() == 40 and exact.count_by_rank(e, levels).first()[0] == exact.count_by_rank(e).first()[0]


def test_wedges_are_drawn_evenly(spark):
    """A hub and a clique: the hub's wedges are none of them closed, and no join is a nested loop of draws and vertices."""
    pairs = [(0, x) for x in range(1, 60)] + list(combinations(range(100, 112), 2))
    e = model.canonical(spark.createDataFrame(pairs, "src long, dst long")).cache()
    r = baselines.wedge_sampling(e, 4000).first()
    assert r["samples"] == 4000 and r["wedges"] == comb(59, 2) + 12 * comb(11, 2)
    assert r["estimate"] == pytest.approx(comb(12, 3), rel=0.2)
    star = model.canonical(spark.createDataFrame([(1, 2)], "src long, dst long"))
    assert baselines.wedge_sampling(star, 10).first()["samples"] == 0


def test_lifted_rows_are_bounded(spark):
    """The lifted graph has at most 2 m alpha^(k-2) edges beside those of the graph."""
    r = random.Random(3)
    e = model.renumbered(model.canonical(spark.createDataFrame([tuple(r.sample(range(30), 2)) for _ in range(160)], "src long, dst long"))).cache()
    m, d = e.count(), orient.degeneracy(e).first()[0]
    for k in (4, 5, 6):
        base = cliques.enumerate_lifted(e, k - 2, peel.schedule("from_bound", 5), 30)
        graph, known = cliques.lifted_graph(e, base, 30)
        assert known.count() == (cliques.count_ordered(e, k - 2).first()[0] if k > 4 else m)
        assert graph.count() - m <= 2 * m * d ** (k - 2)
        assert cliques.count_lifted(e, k).first()[0] == cliques.count_ordered(e, k).first()[0]


def test_the_incremental_count_goes_on_after_a_restart(spark, tmp_path):
    from subcount.streaming import edges as streams

    pairs, at = list(combinations(range(9), 2)), f"{tmp_path}/in"
    read = lambda: spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(at)
    spark.createDataFrame(pairs[:20], "src long, dst long").repartition(2).write.parquet(at)
    streams.incremental_triangles(read(), f"{tmp_path}/state")
    spark.createDataFrame(pairs[15:], "src long, dst long").coalesce(1).write.mode("append").parquet(at)
    assert streams.incremental_triangles(read(), f"{tmp_path}/state").first()[0] == comb(9, 3)
    c = streams.Counter(spark, f"{tmp_path}/state")
    c(spark.createDataFrame(pairs[15:], "src long, dst long"), 2)  # run again
    assert c.total().first()[0] == comb(9, 3)


def test_edge_lists_in_ranges_of_bytes(spark, tmp_path):
    from subcount.sources import edges as sources

    r = random.Random(1)
    pairs = [(r.randint(-5, 10**12), r.randint(0, 99)) for _ in range(500)]
    (tmp_path / "a.txt").write_text("# head\n" + "\n".join(f"{a} {b}" for a, b in pairs) + "\nno numbers\n7\n1 2")
    sources.register(spark)
    for parts in (1, 3, 50):
        got = spark.read.format("edgelist").option("path", str(tmp_path / "a.txt")).option("parts", parts).load()
        assert sorted(map(tuple, got.collect())) == sorted([*pairs, (1, 2)])


def test_local_folders_are_for_local_sessions_only():
    from types import SimpleNamespace

    from subcount.storage import checkpoint_dir

    fake = lambda master, named: SimpleNamespace(sparkContext=SimpleNamespace(master=master, getConf=lambda: {"spark.checkpoint.dir": named}))
    with pytest.raises(RuntimeError):
        checkpoint_dir(fake("spark://host:7077", None))
    assert checkpoint_dir(fake("spark://host:7077", "/shared/x/")) == "/shared/x" and checkpoint_dir(fake("local[4]", None))


def test_shared_lines_are_not_shuffled_as_text(spark):
    plan = graphs.sharedline(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert not [x for x in plan.splitlines() if "Exchange" in x and "line#" in x]
