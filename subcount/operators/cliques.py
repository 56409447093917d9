"""Counting k-cliques: by lifted graphs, by ordered extension, by capped neighbourhood pairs."""

from __future__ import annotations

from functools import reduce
from math import comb

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import arcs, renumbered
from ..session import ship
from ..storage import materialize
from . import blocks, exact, peel


def enumerate_ordered(edges: DataFrame, k: int) -> DataFrame:
    """members: sorted ids of every k-clique, once. Grows along a low-out-degree order, one vertex a step."""
    o = exact.ranked(edges)
    copies = o.select(F.array("u", "v").alias("c"))
    if k == 1:
        return arcs(edges).select(F.array("src").alias("members")).distinct()
    for size in range(3, k + 1):
        step = o.select(F.col("u").alias("head"), F.col("v").alias("x"))
        copies = copies.withColumn("head", F.element_at("c", -1)).join(step, "head").drop("head")
        for i in range(size - 2):
            copies = copies.withColumn("u", F.col("c")[i]).join(o.withColumnRenamed("v", "x"), ["u", "x"], "left_semi").drop("u")
        copies = copies.select(F.array_append("c", F.col("x")).alias("c"))
    return copies.select(F.array_sort("c").alias("members"))


MOST_COPIES = 1 << 30  # packed edges that 4-cliques may be counted from


def count_ordered(edges: DataFrame, k: int, most: int = MOST_COPIES) -> DataFrame:
    """k = 3, 4: by ordered extension inside blocks of colours, so neither wedges nor cliques become rows; only where
    blocks of four colours take more than `most` copies of edges, listed triangles are extended inside the links of
    vertices. edges: may be repeated then."""
    if k in (3, 4):
        e = blocks.stored(edges)
        m = blocks.edges_of(e)
        if k == 4 and m * blocks.copies(blocks.colours_for(m, k), k) > most:
            return blocks.count4_by_links(e, m)
        return blocks.count_stored(e, k, m)
    return enumerate_ordered(edges, k).agg(F.count("*").alias("cliques"))


def lifted_graph(edges: DataFrame, cliques: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """The edges of G and those from each clique, as a vertex, to the vertices next to all its members; and the
    numbers of the cliques. edges: vertices 0 .. n - 1; cliques: members (sorted). A clique's number starts at n, so
    members, not a hash, tell lifted vertices apart."""
    both = arcs(edges)
    known = _numbers(cliques, n)
    size = known.select(F.size("members")).first()
    grown = known.select("q", "members", F.col("members")[0].alias("src")).join(both, "src").select("q", "members", F.col("dst").alias("x"))
    for i in range(1, size[0] if size else 1):
        grown = grown.withColumn("src", F.col("members")[i]).join(both.withColumnRenamed("dst", "x"), ["src", "x"], "left_semi").drop("src")
    lifted = grown.select(F.col("x").alias("src"), F.col("q").alias("dst"))
    return materialize(edges.select("src", "dst").unionAll(lifted)), known


def _numbers(cliques: DataFrame, n: int, parts: int = 64) -> DataFrame:
    """q, members: distinct members numbered from n on, by hashed parts and the counts of the parts before."""
    c = materialize(cliques.select("members").distinct().withColumn("part", F.pmod(F.xxhash64("members"), F.lit(parts))))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shift = c.groupBy("part").count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("shift"))
    within = F.row_number().over(Window.partitionBy("part").orderBy("members")) - 1
    numbered = c.withColumn("within", within).join(F.broadcast(shift), "part")
    return materialize(numbered.select((n + F.col("shift") + F.col("within")).alias("q"), "members"))


def lifted_triangles(edges: DataFrame, cliques: DataFrame, n: int, gamma: peel.Schedule) -> DataFrame:
    """members, x < y: triangles of the lifted graph with one lifted vertex, by the lister that peels it."""
    graph, known = lifted_graph(edges, cliques, n)
    t = exact.enumerate_triangles(graph, peel.levels(graph, gamma)).where((F.col("b") < n) & (F.col("c") >= n))
    return t.join(known, F.col("c") == F.col("q")).select("members", F.col("a").alias("x"), F.col("b").alias("y"))


def enumerate_lifted(edges: DataFrame, k: int, gamma: peel.Schedule, n: int) -> DataFrame:
    """members of every k-clique of a graph on 0 .. n - 1: a clique of k - 2 lifted, and a triangle at it."""
    if k == 1:
        return arcs(edges).select(F.array("src").alias("members")).distinct()
    if k == 2:
        return edges.select(F.array("src", "dst").alias("members"))
    if k == 3:
        return exact.enumerate_triangles(edges, peel.levels(edges, gamma)).select(F.array("a", "b", "c").alias("members"))
    t = lifted_triangles(edges, enumerate_lifted(edges, k - 2, gamma, n), n, gamma)
    return t.select(F.array_sort(F.concat("members", F.array("x", "y"))).alias("members")).distinct()


def count_lifted(edges: DataFrame, k: int, gamma: peel.Schedule | None = None) -> DataFrame:
    """Lifts (k-2)-cliques, themselves found so, to vertices next to the vertices that complete them, and counts
    by peeling the triangles with one lifted vertex; a k-clique is seen once for each choice of its lifted part."""
    gamma = gamma or peel.schedule("from_bound", 5)
    if k < 3:
        return count_ordered(edges, k)
    e = materialize(renumbered(edges))
    n = (e.agg(F.max("dst")).first()[0] or 0) + 1
    if k == 3:
        return exact.count_by_rank(e, peel.levels(e, gamma)).select(F.col("triangles").alias("cliques"))
    seen = lifted_triangles(e, enumerate_lifted(e, k - 2, gamma, n), n, gamma).agg(F.count("*").alias("seen"))
    return seen.select(F.expr(f"seen div {comb(k, k - 2)}").alias("cliques"))


def count_local(edges: DataFrame, k: int, delta: float = 0.5, c: float = 4.0, alpha: float = 2.0, patience: int = 20) -> DataFrame:
    """Every vertex of degree at most min(c n^(delta/2), threshold) takes its neighbours and looks for
    (k-1)-cliques among them; a clique with t peeled members is found t times in its round and counts 1/t.
    Lists are bounded by the cap, so one group is one small neighbourhood. The loop ends when no vertex is
    left: after every `patience` rounds at the cap it doubles, so slow peeling takes logarithmically many caps."""
    n = arcs(edges).agg(F.count_distinct("src")).first()[0]
    cap, grow = max(2.0, c * n ** (delta / 2)), peel.schedule("scaled", alpha=alpha)
    # while the cap binds, survivors are peeled at the cap again; once nothing goes, the cap doubles
    now, parts, i, at_cap = materialize(arcs(edges)), [], 0, 0
    spark = edges.sparkSession
    while True:
        if at_cap == patience:
            cap, at_cap = 2 * cap, 0
        bound = min(cap, grow(i))
        deg = materialize(now.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")).withColumn("low", F.col("deg") <= bound))
        left, peeled = deg.agg(F.count("*"), F.count_if("low")).first()
        if not left:
            break
        if not peeled:
            if bound >= cap:
                cap, at_cap = 2 * cap, 0
            i += 1
            continue
        at_cap += bound >= cap
        low = deg.where("low").select("v")
        parts.append(materialize(_local_round(now, low, k)))
        stay = deg.where("not low").select("v")
        now = materialize(now.join(stay.withColumnRenamed("v", "src"), "src", "left_semi").join(stay.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst"))
        i += 1
    if not parts:
        return spark.createDataFrame([(0,)], "cliques long")
    total = reduce(DataFrame.unionAll, parts).groupBy("t").agg(F.sum("found").alias("found"))
    return total.agg(F.coalesce(F.sum(F.expr("found div t")), F.lit(0)).alias("cliques"))


def _local_round(now: DataFrame, low: DataFrame, k: int) -> DataFrame:
    """t, found: cliques found at peeled vertices by their number of peeled members."""
    near = now.join(low.select(F.col("v").alias("src")), "src", "left_semi")
    flagged = near.join(low.select(F.col("v").alias("dst"), F.lit(1).alias("l")), "dst", "left").select("src", F.col("dst").alias("x"), F.coalesce("l", F.lit(0)).alias("lx"))
    y = flagged.select("src", F.col("x").alias("y"), F.col("lx").alias("ly"))
    pair = flagged.join(y, "src").where("x < y").join(now.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"], "left_semi")
    if k == 3:
        return pair.groupBy((F.col("lx") + F.col("ly") + 1).alias("t")).agg(F.count("*").alias("found"))

    def local(group: pa.Table) -> pa.Table:
        adj: dict[int, set[int]] = {}
        flag: dict[int, int] = {}
        for x, y, lx, ly in zip(*(group[c].to_pylist() for c in ("x", "y", "lx", "ly"))):
            adj.setdefault(x, set()).add(y)
            flag[x], flag[y] = lx, ly
        found: dict[int, int] = {}

        def extend(common, size, t):
            if size == k - 1:
                found[t] = found.get(t, 0) + 1
                return
            for z in common:
                extend(common & adj.get(z, set()), size + 1, t + flag[z])

        for x in adj:
            extend(adj[x], 1, 1 + flag[x])
        return pa.table({"t": pa.array(found.keys(), pa.int32()), "found": pa.array(found.values(), pa.int64())})

    ship(now.sparkSession)
    return pair.groupBy("src").applyInArrow(local, "t int, found long").groupBy("t").agg(F.sum("found").alias("found"))
