"""Exact triangle counting and listing."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import arcs, degrees
from . import blocks, peel


def ranked(edges: DataFrame, levels: DataFrame | None = None) -> DataFrame:
    """Edges from lower to higher (level, degree, id), as u, v; without levels by (degree, id)."""
    deg = degrees(edges)
    rank = deg.select("v", F.struct(F.lit(0).alias("l"), "deg", "v").alias("r"))
    if levels is not None:
        rank = deg.join(levels.select("v", "level"), "v", "left").select("v", F.struct(F.coalesce("level", F.lit(1 << 30)).alias("l"), "deg", "v").alias("r"))
    a = rank.select(F.col("v").alias("src"), F.col("r").alias("ra"))
    b = rank.select(F.col("v").alias("dst"), F.col("r").alias("rb"))
    e = edges.join(a, "src").join(b, "dst")
    up = F.col("ra") < F.col("rb")
    return e.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("v"))


def close_wedges(oriented: DataFrame, edges: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Triangles (u; v < w): out-wedges at u whose ends are joined. keys: columns all three edges share."""
    x, y = oriented.select(*keys, "u", "v"), oriented.select(*keys, "u", F.col("v").alias("w"))
    wedge = x.join(y, [*keys, "u"]).where("v < w")
    return wedge.join(edges.select(*keys, F.col("src").alias("v"), F.col("dst").alias("w")), [*keys, "v", "w"])


def enumerate_triangles(edges: DataFrame, levels: DataFrame | None = None) -> DataFrame:
    """a < b < c of every triangle, once."""
    t = close_wedges(ranked(edges, levels), edges)
    return t.select(F.least("u", "v").alias("a"), F.when(F.col("u") < F.col("v"), F.col("v")).when(F.col("u") < F.col("w"), F.col("u")).otherwise(F.col("w")).alias("b"), F.greatest("u", "w").alias("c"))


def count_by_rank(edges: DataFrame, levels: DataFrame | None = None) -> DataFrame:
    """One row: triangles. Two exchanges of wedge rows, bounded by the orientation's out-degrees."""
    return close_wedges(ranked(edges, levels), edges).agg(F.count("*").alias("triangles"))


def messages(r: peel.Round) -> DataFrame:
    """(w, v): what each neighbour w of a peeled vertex hears of its neighbours."""
    from_low = r.arcs.join(r.low().select(F.col("v").alias("src")), "src", "left_semi")
    return from_low.select("src", F.col("dst").alias("w")).join(from_low.select("src", F.col("dst").alias("v")), "src").where("w <> v").select("w", "v")


def pair_counts(r: peel.Round) -> DataFrame:
    """(w, v, heard): neighbours w, v of the surviving graph and their number of peeled common neighbours."""
    own = r.arcs.select(F.col("src").alias("w"), F.col("dst").alias("v"), F.lit(1).alias("own"))
    both = messages(r).withColumn("own", F.lit(0)).unionAll(own)
    return both.groupBy("w", "v").agg((F.count("*") - 1).alias("heard"), F.max("own").alias("own")).where("own = 1 and heard > 0").drop("own")


def class_totals(r: peel.Round, pairs: DataFrame | None = None) -> DataFrame:
    """found2, found4, found6: heard counts of pairs with none, one or both ends peeled now."""
    low = r.low()
    pairs = pair_counts(r) if pairs is None else pairs
    p = pairs.join(low.select(F.col("v").alias("w"), F.lit(1).alias("lw")), "w", "left").join(low.select("v", F.lit(1).alias("lv")), "v", "left")
    ends = F.coalesce("lw", F.lit(0)) + F.coalesce("lv", F.lit(0))
    return p.agg(*[F.coalesce(F.sum(F.when(ends == k, F.col("heard"))), F.lit(0)).alias(f"found{2 * k + 2}") for k in range(3)])


def duplicates_trace(edges: DataFrame, gamma: peel.Schedule, traced: peel.Trace | None = None) -> DataFrame:
    """round, gamma, vertices, edges, peeled, messages, found2, found4, found6. What the pairs of a round hear is counted
    in blocks of colours, triangle by triangle; no message is a row (pair_counts has them as rows)."""
    t = traced or peel.rounds(edges, gamma)
    kind = "round int, gamma double, vertices long, edges long, peeled long, messages long"
    if not t.rounds:
        return edges.sparkSession.createDataFrame([], f"{kind}, found2 long, found4 long, found6 long")
    low = reduce(DataFrame.unionAll, [r.low().select("v", F.lit(r.number).alias("level")) for r in t.rounds])
    heard = blocks.by_level(t.rounds[0].arcs.where("src < dst"), low)
    # a triangle whose first j vertices go together is heard by both ends of its j pairs that see one of them go
    found = [F.coalesce(F.sum(F.when(F.col("lowest") == j, 2 * j * F.col("triangles"))), F.lit(0)).alias(f"found{2 * j}") for j in (1, 2, 3)]
    by_round = peel.trace_table(edges.sparkSession, t).join(heard.withColumnRenamed("level", "round"), "round", "left")
    return by_round.groupBy("round", "gamma", "vertices", "edges", "peeled", "messages").agg(*found).select(F.col("round").cast("int"), *[x.split()[0] for x in kind.split(", ")[1:]], "found2", "found4", "found6")


def count_by_duplicates(edges: DataFrame, gamma: peel.Schedule, corrected: bool = True, traced: peel.Trace | None = None) -> DataFrame:
    """One row: triangles (and raw, the sum before correction)."""
    total = duplicates_trace(edges, gamma, traced).agg(*[F.coalesce(F.sum(f"found{k}"), F.lit(0)).alias(f"f{k}") for k in (2, 4, 6)])
    raw = (F.col("f2") + F.col("f4") + F.col("f6")).alias("raw")
    exact = F.expr("f2 div 2 + f4 div 4 + f6 div 6").alias("triangles")
    return total.select(exact, raw) if corrected else total.select(raw)


def count_by_edge_class(edges: DataFrame, gamma: peel.Schedule, traced: peel.Trace | None = None) -> DataFrame:
    """One row: triangles, by edges w < v: peeled common neighbours over one plus the peeled ends."""
    t = traced or peel.rounds(edges, gamma)
    parts = []
    for r in t.rounds:
        own = r.arcs.where("src < dst").select(F.col("src").alias("w"), F.col("dst").alias("v"))
        heard = messages(r).where("w < v").groupBy("w", "v").agg(F.count("*").alias("heard"))
        parts.append(class_totals(r, heard.join(own, ["w", "v"], "left_semi")))
    if not parts:
        return edges.sparkSession.createDataFrame([(0,)], "triangles long")
    total = reduce(DataFrame.unionAll, parts).agg(*[F.sum(f"found{k}").alias(f"f{k}") for k in (2, 4, 6)])
    return total.select(F.expr("f2 + f4 div 2 + f6 div 3").alias("triangles"))


def triangles_at(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """a < b < c of the triangles with at least one of the vertices (column v), once."""
    near = arcs(edges).join(vertices.select(F.col("v").alias("src")).distinct(), "src", "left_semi")
    wedge = near.select("src", F.col("dst").alias("x")).join(near.select("src", F.col("dst").alias("y")), "src").where("x < y")
    t = wedge.join(edges.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"])
    s = F.array_sort(F.array("src", "x", "y"))
    return t.select(s[0].alias("a"), s[1].alias("b"), s[2].alias("c")).distinct()


def enumerate_by_rounds(edges: DataFrame, gamma: peel.Schedule) -> DataFrame:
    """All triangles as the union over rounds of those at the vertices peeled."""
    t = peel.rounds(edges, gamma)
    parts = [triangles_at(r.arcs.where("src < dst"), r.low()) for r in t.rounds]
    return reduce(DataFrame.unionAll, parts) if parts else edges.sparkSession.createDataFrame([], "a long, b long, c long")


def per_vertex(edges: DataFrame) -> DataFrame:
    """v, deg, triangles, clustering."""
    t = enumerate_triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count("*").alias("triangles"))
    d = degrees(edges).join(t, "v", "left").withColumn("triangles", F.coalesce("triangles", F.lit(0)))
    return d.withColumn("clustering", F.when(F.col("deg") > 1, F.round(2 * F.col("triangles") / (F.col("deg") * (F.col("deg") - 1)), 6)).otherwise(0.0))


def per_edge(edges: DataFrame) -> DataFrame:
    """src, dst, support."""
    ends = F.explode(F.array(*[F.struct(F.col(x).alias("src"), F.col(y).alias("dst")) for x, y in (("a", "b"), ("a", "c"), ("b", "c"))]))
    s = enumerate_triangles(edges).select(ends.alias("e")).groupBy("e.src", "e.dst").agg(F.count("*").alias("support"))
    return edges.join(s, ["src", "dst"], "left").select("src", "dst", F.coalesce("support", F.lit(0)).alias("support"))


def clustering(edges: DataFrame) -> DataFrame:
    """wedges, triangles, global clustering and the mean of the local ones."""
    v = per_vertex(edges)
    c = v.agg(F.sum(F.expr("deg * (deg - 1) div 2")).alias("wedges"), F.expr("sum(triangles) div 3").alias("triangles"), F.round(F.avg("clustering"), 6).alias("mean_local"))
    return c.withColumn("global", F.round(3 * F.col("triangles") / F.col("wedges"), 6))
