"""The experiment workloads on derived graphs."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import graphs
from ..model import degrees, size
from ..storage import materialize
from . import approx, baselines, blocks, exact, measures, orient, patterns, peel

ROUND_GRAPHS = {"lexical": (5, 10), "tripartite": (5, 10), "copart30": (5, 10), "sharedline": (10, 20), "copurchase": (2, 10)}
FACTOR_GRAPHS = ("tripartite", "copurchase", "cosupply", "sharedline")
AT_ONCE = 6  # graphs whose jobs the driver hands in side by side


def side_by_side(work: Callable, items: Iterable) -> list:
    """work of each item, in their order; the many small jobs of one leave cores to those of the others."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(inheritable_thread_target(work), items))


def graph_stats(spark: SparkSession, d: str, name: str) -> DataFrame:
    """graph, n, m, triangles, max_degree."""
    e = blocks.stored(graphs.pairs(spark, d, name))
    m = blocks.edges_of(e)
    deg = materialize(blocks.degrees_of(e).agg(F.count("*").alias("n"), F.coalesce(F.max("deg"), F.lit(0)).alias("max_degree")))
    t = blocks.count_stored(e, 3, m).withColumnRenamed("cliques", "triangles")
    return t.join(F.broadcast(deg)).select(F.lit(name).alias("graph"), "n", F.lit(m).cast("long").alias("m"), "triangles", "max_degree")


def graph_table(spark: SparkSession, d: str) -> DataFrame:
    """graph, n, m, triangles, max_degree, degeneracy of all graphs."""

    def row(name: str) -> DataFrame:
        core = orient.degeneracy(materialize(graphs.GRAPHS[name](spark, d))).first()[0]
        return graph_stats(spark, d, name).withColumn("degeneracy", F.lit(int(core)).cast("long"))

    return reduce(DataFrame.unionAll, side_by_side(row, graphs.GRAPHS))


def scaling(spark: SparkSession, d: str, name: str = "tripartite", parts: int = 4) -> DataFrame:
    """part, edges, triangles, exchanges: the count on growing shares of the graph, those of the first k of `parts`
    classes of vertices by id; its plan has the same exchanges at each size."""
    e = materialize(graphs.numbered(spark, d, name))
    out = []
    for k in range(1, parts + 1):
        share = e.where(f"src % {parts} < {k} and dst % {parts} < {k}")
        t = blocks.count(share).withColumnRenamed("cliques", "triangles")
        shape = measures.plan_stats(t)
        m = share.agg(F.count("*").alias("edges"))
        out.append(t.join(F.broadcast(m)).select(F.lit(k).alias("part"), "edges", "triangles", F.lit(shape["exchanges"]).alias("exchanges")))
    return reduce(DataFrame.unionAll, out)


def rounds(spark: SparkSession, d: str, name: str) -> DataFrame:
    """graph, bound, space, method, iterations, model_rounds, messages: by start bound and space per machine,
    doubly exponential thresholds against the constant one, which exists at the degeneracy only."""
    e = materialize(graphs.GRAPHS[name](spark, d))
    n = size(e).first()[0]
    core = orient.degeneracy(e).first()[0]
    spaces = {s: n**s for s in (0.3, 0.5, 0.9)}
    runs = [(b, "growing", "from_bound") for b in sorted({*ROUND_GRAPHS[name], core})] + [(core, "constant", "constant")]
    rows = []
    for (bound, method, _), t in zip(runs, orient.traces(e, [(kind, b) for b, _, kind in runs])):
        for delta, s in spaces.items():
            total = sum(measures.rounds_of(messages + 2 * edges, s) for *_, edges, _, messages in t)
            rows.append((name, int(bound), float(delta), method, len(t), total, sum(r[-1] for r in t)))
    return spark.createDataFrame(rows, "graph string, bound int, delta double, method string, iterations int, model_rounds int, messages long")


def stalls(spark: SparkSession, d: str, names: tuple[str, ...]) -> DataFrame:
    """The constant threshold one under the degeneracy: what is left."""

    def row(name: str) -> tuple:
        e = materialize(graphs.GRAPHS[name](spark, d))
        core = orient.degeneracy(e).first()[0] or 0
        t = peel.rounds(e, peel.schedule("constant", core - 1))
        return name, int(core) - 1, t.stalled, t.left_vertices, t.left_edges

    return spark.createDataFrame(side_by_side(row, names), "graph string, bound int, stalled boolean, left_vertices long, left_edges long")


def factors(spark: SparkSession, d: str, names: tuple[str, ...], delta: float, groups: int = 3, per_group: int = 2, seed: int = 1) -> DataFrame:
    """graph, delta, method, machines, estimate, factor: median of means of both estimators."""
    out = []
    for name in names:
        e = materialize(graphs.numbered(spark, d, name))
        p = approx.for_graph(e, delta=delta, seed=seed)
        truth = exact.count_by_rank(e)
        ours = approx.estimate_mom(e, p, groups, per_group)
        colours = baselines.colours_for(p.n, p.m, p.space)
        c = baselines.colour_partition(e, colours, seed, groups * per_group).groupBy((F.col("rep") % groups).alias("g")).agg(F.avg("estimate").alias("mean"))
        for method, est in (("overlapping samples", ours), ("colour partition", approx.lower_median(c, "mean"))):
            f = measures.factor(est, truth)
            out.append(f.select(F.lit(name).alias("graph"), F.lit(delta).alias("delta"), F.lit(method).alias("method"), F.lit(p.machines).alias("machines"), F.round("estimate", 3).alias("estimate"), "factor"))
    return reduce(DataFrame.unionAll, out)


def _truth(cells: DataFrame) -> DataFrame:
    return materialize(blocks.count_stored(cells).withColumnRenamed("cliques", "triangles"))


def hash_ablation(spark: SparkSession, d: str, name: str = "tripartite", delta: float = 0.75, reps: int = 3) -> DataFrame:
    e = blocks.stored(graphs.numbered(spark, d, name) if name in graphs.KEYED else graphs.pairs(spark, d, name))
    p = approx.for_graph(e, delta=delta)
    truth = _truth(e)
    parts = [measures.factor(approx.estimate_median(e, p, reps, hash_=h), truth).select(F.lit(h).alias("hash"), "factor") for h in ("kwise", "mixed")]
    return reduce(DataFrame.unionAll, parts)


def correction(spark: SparkSession, d: str, names: tuple[str, ...]) -> DataFrame:
    """graph, raw, triangles, ratio (between 2 and 6)."""

    def row(name: str) -> DataFrame:
        c = exact.count_by_duplicates(graphs.GRAPHS[name](spark, d), peel.schedule("from_bound", 5))
        return c.select(F.lit(name).alias("graph"), "raw", "triangles", F.round(F.try_divide("raw", "triangles"), 6).alias("ratio"))

    return reduce(DataFrame.unionAll, side_by_side(row, names))


def below_bound(spark: SparkSession, d: str, reps: int = 20, p: float = 0.05, machines: int = 20) -> DataFrame:
    """Few triangles: coverage is low, and the plan says so."""
    e = blocks.stored(graphs.pairs(spark, d, "vecsim"))
    truth = _truth(e).first()[0]
    plan = approx.for_graph(e, mode="explicit", p=p, machines=machines, k=6, space=blocks.edges_of(e))
    c = measures.coverage(approx.estimates(e, plan, reps), truth, 0.5)
    return c.withColumn("expected_hits", F.lit(round(measures.theory(plan, truth)["expected_hits"], 6)))


def pattern_suite(spark: SparkSession, d: str, name: str, which: tuple[str, ...]) -> DataFrame:
    """pattern, copies; what blocks.fours counts comes from one run of it."""
    e = materialize(graphs.GRAPHS[name](spark, d))
    fours = materialize(blocks.fours(e)) if set(which) & set(blocks.FOURS) else None
    one = lambda w: fours.select(F.col(w).alias("copies")) if w in blocks.FOURS else patterns.count(e, w)
    return reduce(DataFrame.unionAll, [one(w).select(F.lit(w).alias("pattern"), "copies") for w in which])
