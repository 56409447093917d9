"""Earlier methods the measures are compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import arcs, degrees
from ..storage import materialize
from . import exact, hashing, orient, peel


def brute(edges: DataFrame) -> DataFrame:
    """Three-way self join a < b < c."""
    e = edges
    t = e.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(e.select(F.col("src").alias("b"), F.col("dst").alias("c")), "b")
    return t.join(e.select(F.col("src").alias("a"), F.col("dst").alias("c")), ["a", "c"]).agg(F.count("*").alias("triangles"))


def peel_constant(edges: DataFrame, g: int) -> DataFrame:
    """Constant threshold: triangles, passes, stalled and what is left."""
    t = peel.rounds(edges, peel.schedule("constant", g))
    out = exact.count_by_duplicates(edges, None, traced=t).select("triangles")
    facts = (("passes", len(t.rounds)), ("left_vertices", t.left_vertices), ("left_edges", t.left_edges))
    return out.select("triangles", *[F.lit(v).cast("long").alias(k) for k, v in facts], F.lit(t.stalled).alias("stalled"))


def folklore(edges: DataFrame, alpha: int) -> DataFrame:
    """Peel at 2 alpha, put a vertex's out-neighbours on one machine, ask for all pairs."""
    o = orient.by_levels(edges, peel.schedule("constant", 2 * alpha)).select(F.col("src").alias("u"), F.col("dst").alias("v"))
    own = o.groupBy("u").agg(F.sort_array(F.collect_list("v")).alias("out"))
    pair = own.select("out", F.posexplode("out").alias("i", "v")).select("v", F.explode(F.expr("slice(out, i + 2, size(out))")).alias("w"))
    return pair.join(edges.select(F.col("src").alias("v"), F.col("dst").alias("w")), ["v", "w"]).agg(F.count("*").alias("triangles"))


def two_round(edges: DataFrame) -> DataFrame:
    """Wedges at the lower end by (degree, id), then closing: two rounds."""
    return exact.close_wedges(exact.ranked(edges), edges).agg(F.count("*").alias("triangles"))


def one_round(edges: DataFrame, buckets: int = 4) -> DataFrame:
    """Vertices in buckets, one machine per triple of buckets; every edge goes to all triples that hold its
    ends; a triangle counts where the triple is its own buckets, sorted."""
    b = lambda c: F.pmod(F.xxhash64(c), F.lit(buckets)).cast("int")
    e = edges.withColumn("x", b("src")).withColumn("y", b("dst")).withColumn("z", F.explode(F.sequence(F.lit(0), F.lit(buckets - 1))))
    e = e.select("src", "dst", F.array_sort(F.array("x", "y", "z")).alias("cell")).distinct()
    t = e.select("cell", F.col("src").alias("a"), F.col("dst").alias("b")).join(e.select("cell", F.col("src").alias("b"), F.col("dst").alias("c")), ["cell", "b"])
    t = t.join(e.select("cell", F.col("src").alias("a"), F.col("dst").alias("c")), ["cell", "a", "c"])
    return t.where(F.col("cell") == F.array_sort(F.array(b("a"), b("b"), b("c")))).agg(F.count("*").alias("triangles"))


def vertex_sweep(edges: DataFrame, batches: int = 4) -> DataFrame:
    """Round after round one batch of vertices with linear memory: triangles whose least vertex is in it."""
    out = None
    for k in range(batches):
        first = edges.where(F.pmod(F.xxhash64("src"), F.lit(batches)) == k)
        x = first.select(F.col("src").alias("a"), F.col("dst").alias("b"))
        t = x.join(x.withColumnRenamed("b", "c"), "a").where("b < c").join(edges.select(F.col("src").alias("b"), F.col("dst").alias("c")), ["b", "c"])
        here = t.agg(F.count("*").alias("t"))
        out = here if out is None else out.unionAll(here)
    return out.agg(F.sum("t").alias("triangles"))


def edge_intersection(edges: DataFrame) -> DataFrame:
    """Size of the intersection of out-neighbour lists at each edge."""
    o = exact.ranked(edges)
    out = o.groupBy("u").agg(F.collect_list("v").alias("out"))
    e = o.join(out, "u").join(out.select(F.col("u").alias("v"), F.col("out").alias("other")), "v")
    return e.agg(F.coalesce(F.sum(F.size(F.array_intersect("out", "other"))), F.lit(0)).cast("long").alias("triangles"))


def colour_partition(edges: DataFrame, colours: int, seed: int = 1, reps: int = 1) -> DataFrame:
    """rep, hits, estimate: keep edges of one colour, count triangles, times colours squared. Ids have 31 bits."""
    out = None
    for rep in range(reps):
        c = hashing.coefficients(4, seed, rep)
        colour = lambda v: hashing.kwise(hashing.checked(F.col(v), hashing.P31), c) % colours  # noqa: E731, B023
        e = edges.withColumn("i", colour("src")).where(F.col("i") == colour("dst")).select("i", "src", "dst")
        t = exact.close_wedges(e.select("i", F.col("src").alias("u"), F.col("dst").alias("v")), e, ("i",))
        here = t.agg(F.count("*").alias("hits")).select(F.lit(rep).alias("rep"), "hits")
        out = here if out is None else out.unionAll(here)
    return out.withColumn("estimate", F.col("hits").cast("double") * colours * colours)


def colours_for(n: int, m: int, space: int, how: str = "machines") -> int:
    total = int(2 * m * math.log(max(2, m)))
    return max(1, -(-total // space)) if how == "machines" else max(1, math.ceil(math.sqrt(m / space)))


def wedge_sampling(edges: DataFrame, samples: int = 1000, seed: int = 1, lots: int = 256) -> DataFrame:
    """hits, samples, estimate: wedges drawn evenly (by a hash, so retries draw the same), share closed.

    Vertices are dealt to lots; a draw is a number under the sum of all wedges, which names a lot, then a bucket
    of the lot's cumulative weights, so draws meet vertices by equality. A lot has as many buckets as vertices, so a
    bucket holds few, and a vertex lies in as many more buckets as its weight fills.
    """
    spark = edges.sparkSession
    deg = degrees(edges).withColumn("w", F.expr("deg * (deg - 1) div 2")).where("w > 0")
    lot = deg.withColumn("lot", F.pmod(F.xxhash64("v"), F.lit(lots)))
    before = Window.orderBy("lot").rowsBetween(Window.unboundedPreceding, -1)
    base = lot.groupBy("lot").agg(F.sum("w").alias("s"), F.count("*").alias("c")).withColumn("base", F.coalesce(F.sum("s").over(before), F.lit(0)))
    base = base.withColumn("width", F.greatest(F.lit(1), F.ceil(F.col("s") / F.col("c"))).cast("long"))
    base = materialize(base)  # at most `lots` rows
    total = base.agg(F.sum("s")).first()[0] or 0
    rows = [F.struct(*[F.lit(x).cast("long").alias(n) for n, x in zip(("lot", "base", "width"), r)]) for r in base.select("lot", "base", "width").orderBy("base").collect()]
    none = F.array().cast("array<struct<lot:long,base:long,width:long>>")
    x = F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(max(1, total)))
    draws = spark.range(samples if total else 0).select("id", x.alias("x"))
    draws = draws.withColumn("l", F.element_at(F.filter(F.array(*rows) if rows else none, lambda r: r["base"] <= F.col("x")), -1))
    draws = draws.select("id", "l.lot", (F.col("x") - F.col("l.base")).alias("r")).join(F.broadcast(base.select("lot", "width")), "lot")
    draws = draws.select("id", "lot", "r", F.expr("r div width").alias("bucket"))
    within = Window.partitionBy("lot").orderBy("v").rowsBetween(Window.unboundedPreceding, -1)
    lo = lot.withColumn("lo", F.coalesce(F.sum("w").over(within), F.lit(0))).join(F.broadcast(base.select("lot", "width")), "lot")
    spread = lo.select("lot", "v", "w", "lo", F.explode(F.expr("sequence(lo div width, (lo + w - 1) div width)")).alias("bucket"))
    hit = draws.join(spread, ["lot", "bucket"]).where("r >= lo and r < lo + w")
    r = (F.col("r") - F.col("lo")).cast("double")
    hit = hit.withColumn("j", F.floor((1 + F.sqrt(1 + 8 * r)) / 2)).withColumn("i", F.col("r") - F.col("lo") - F.expr("j * (j - 1) div 2"))
    order = F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1
    wanted = arcs(edges).join(hit.select(F.col("v").alias("src")).distinct(), "src", "left_semi").withColumn("k", order)
    a = wanted.select(F.col("src").alias("v"), F.col("k").alias("i"), F.col("dst").alias("a"))
    b = wanted.select(F.col("src").alias("v"), F.col("k").alias("j"), F.col("dst").alias("b"))
    pair = hit.join(a, ["v", "i"]).join(b, ["v", "j"]).select("id", F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
    closed = pair.join(edges.withColumn("c", F.lit(1)), ["src", "dst"], "left")
    out = closed.agg(F.count("c").alias("hits"), F.count("*").alias("samples")).withColumn("wedges", F.lit(total).cast("long"))
    return out.withColumn("estimate", F.try_divide(F.col("hits"), F.col("samples")) * F.col("wedges") / 3)
