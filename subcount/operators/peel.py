"""Peeling of low-degree vertices under growing thresholds."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import arcs
from ..storage import forget, materialize

Schedule = Callable[[int], float]


def schedule(kind: str = "from_bound", g0: float = 2, alpha: float | None = None) -> Schedule:
    """Thresholds by round, from 0: plain 2^(1.5^i), scaled 2 alpha times that, from_bound g0^(1.5^i), constant g0."""
    grow = lambda b, i: b ** (1.5**i) if (1.5**i) * math.log(max(b, 2)) < 600 else math.inf
    kinds = {
        "plain": lambda i: grow(2, i),
        "scaled": lambda i: 2 * alpha * grow(2, i),
        "from_bound": lambda i: grow(g0, i),
        "constant": lambda i: float(g0),
    }
    if kind not in kinds:
        raise ValueError(f"no schedule {kind}; there are {sorted(kinds)}")
    if kind == "scaled" and not alpha:
        raise ValueError("the scaled schedule needs alpha")
    return kinds[kind]


def rounds_needed(n: int) -> int:
    """Rounds after which the plain threshold is n at least."""
    return max(1, math.ceil(math.log(max(2.0, math.log2(max(4, n))), 1.5)) + 1)


@dataclass
class Round:
    """One pass: arcs of the surviving graph, and its vertices with degree and whether they go now."""

    number: int
    gamma: float
    arcs: DataFrame
    vertices: DataFrame  # v, deg, low
    n: int
    edges: int
    peeled: int
    messages: int

    def low(self) -> DataFrame:
        return self.vertices.where("low").select("v", "deg")


@dataclass
class Trace:
    rounds: list[Round]
    stalled: bool = False
    left_vertices: int = 0
    left_edges: int = 0


def rounds(edges: DataFrame, gamma: Schedule, max_rounds: int | None = None, keep: bool = True) -> Trace:
    """Peel until no vertex is left. Each round is two written tables and one row for the driver. A trace that
    max_rounds would cut is an error. keep: if not, a round's tables are removed after it, and only its numbers stay."""
    now, trace, i = materialize(arcs(edges)), Trace([]), 0
    while True:
        g = gamma(i)
        cut = F.lit(True) if math.isinf(g) else F.col("deg") <= g
        v = materialize(now.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")).withColumn("low", cut))
        low = F.when(F.col("low"), F.col("deg"))
        n, m, peeled, sent = v.agg(F.count("*"), F.sum("deg"), F.count(low), F.coalesce(F.sum(low * low), F.lit(0))).first()
        if not n:
            return trace
        if not peeled and gamma(i + 1) <= g:
            return Trace(trace.rounds, True, n, m // 2)
        if max_rounds is not None and i >= max_rounds:
            raise RuntimeError(f"{n} vertices and {m // 2} edges are left after {max_rounds} rounds")
        trace.rounds.append(Round(i, g, now, v, n, m // 2, peeled, sent))
        if peeled == n:
            return trace
        if peeled:
            stay = v.where("not low")
            was, now = now, now.join(stay.select(F.col("v").alias("src")), "src", "left_semi").join(stay.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst")
            now = materialize(now)
            if not keep:
                forget(was)
                forget(v)
        i += 1
        # vertices whose last neighbour went have no arcs left; they leave with that neighbour's round


def levels(edges: DataFrame, gamma: Schedule, traced: Trace | None = None) -> DataFrame:
    """v, level, deg_at_removal. A vertex left without edges gets the level after its last neighbour's."""
    t = traced or rounds(edges, gamma)
    spark = edges.sparkSession
    out = spark.createDataFrame([], "v long, level int, deg_at_removal long")
    for r in t.rounds:
        out = out.unionAll(r.low().select("v", F.lit(r.number).alias("level"), F.col("deg").alias("deg_at_removal")))
    rest = arcs(edges).select(F.col("src").alias("v")).distinct().join(out, "v", "left_anti")
    if t.stalled:
        return out
    seen = None
    for r in t.rounds:
        here = r.vertices.select("v", F.lit(r.number + 1).alias("level"))
        seen = here if seen is None else seen.unionAll(here)
    if seen is None:
        return out
    bare = rest.join(seen, "v").groupBy("v").agg(F.max("level").cast("int").alias("level")).withColumn("deg_at_removal", F.lit(0).cast("long"))
    return out.unionAll(bare.select("v", "level", "deg_at_removal"))


def trace_table(spark, t: Trace) -> DataFrame:
    rows = [(r.number, float(r.gamma), r.n, r.edges, r.peeled, r.messages) for r in t.rounds]
    return spark.createDataFrame(rows, "round int, gamma double, vertices long, edges long, peeled long, messages long")
