"""Rewrites at the DataFrame level, each with a switch, and the choice of method from a graph's sizes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import degrees
from ..operators import approx, baselines, exact, patterns, peel, primitives


@dataclass(frozen=True)
class Facts:
    n: int
    m: int
    most: int  # largest degree
    wedges: int  # sum of squared degrees

    @property
    def mean(self) -> float:
        return 2 * self.m / max(1, self.n)


def facts(edges: DataFrame) -> Facts:
    """One aggregation over the degrees."""
    r = degrees(edges).agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0)), F.coalesce(F.max("deg"), F.lit(0)), F.coalesce(F.sum(F.col("deg") * F.col("deg")), F.lit(0))).first()
    return Facts(r[0], r[1] // 2, r[2], r[3])


@dataclass(frozen=True)
class Rules:
    rank_triangles: bool = True  # R1: triangles by one oriented wedge join
    edge_class: bool = True  # R2: half the rows of the duplicate count
    distinct_members: bool = True  # R3: membership against distinct keys
    list_samples: bool = True  # R4: hash once per (vertex, machine), not per (edge, machine)
    filter_first: bool = True  # R5: a vertex filter goes below the closing join
    symmetric: bool = True  # R6: order on ids instead of dividing by automorphisms
    finish_by_broadcast: bool = True  # R7: stop peeling when what is left is small


def triangles(edges: DataFrame, rules: Rules = Rules(), known: Facts | None = None) -> DataFrame:
    """Degree order bounds out-degrees by sqrt(2 m); where hubs make even that too many wedges, levels of a few
    peeling passes go before the degree."""
    if not rules.rank_triangles:
        gamma = peel.schedule("from_bound", max(4, (known or facts(edges)).mean))
        return (exact.count_by_edge_class if rules.edge_class else exact.count_by_duplicates)(edges, gamma).select("triangles")
    f = known or facts(edges)
    if f.most <= 64 * max(1.0, f.mean):
        return exact.count_by_rank(edges)
    return exact.count_by_rank(edges, peel.levels(edges, peel.schedule("from_bound", max(4, f.mean))))


def members(queries: DataFrame, of: DataFrame, keys: list[str], rules: Rules = Rules()) -> DataFrame:
    if rules.distinct_members:
        return queries.join(of.select(*keys).distinct(), keys, "left_semi")
    return primitives.member(queries, of, keys).where("is_member").drop("is_member")


def samples(edges: DataFrame, plan: approx.Plan, rules: Rules = Rules()) -> DataFrame:
    """Lists cost n M hashes and two joins, inline 2 m M hashes and none."""
    cheap_inline = plan.m * plan.machines * plan.k < 10**7
    return approx.assign(edges, plan, how="inline" if not rules.list_samples or cheap_inline else "lists")


def triangles_at(edges: DataFrame, vertices: DataFrame, rules: Rules = Rules()) -> DataFrame:
    if rules.filter_first:
        return exact.triangles_at(edges, vertices)
    v = vertices.select("v").distinct()
    t = exact.enumerate_triangles(edges).withColumn("m", F.explode(F.array("a", "b", "c")))
    return t.join(v.withColumnRenamed("v", "m"), "m", "left_semi").select("a", "b", "c").distinct()


def cliques4(edges: DataFrame, rules: Rules = Rules()) -> DataFrame:
    from ..operators import cliques

    if rules.symmetric:
        return cliques.count_ordered(edges, 4)
    return patterns.brute(edges, "k4").select(F.col("copies").alias("cliques"))


def levels(edges: DataFrame, gamma: peel.Schedule, rules: Rules = Rules(), small: int = 100_000) -> DataFrame:
    """Peeling that ends when the survivors are few, or a constant threshold stalls: they get one last level, told
    apart by degree."""
    if not rules.finish_by_broadcast:
        return peel.levels(edges, gamma)
    from ..model import arcs
    from ..storage import materialize

    now, out, i = materialize(arcs(edges)), edges.sparkSession.createDataFrame([], "v long, level int"), 0
    while True:
        deg = materialize(now.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")))
        left = deg.agg(F.coalesce(F.sum("deg"), F.lit(0))).first()[0]
        if left <= 2 * small:
            return out.unionAll(deg.select("v", F.lit(i).alias("level")))
        low = F.col("deg") <= gamma(i)
        if gamma(i + 1) <= gamma(i) and deg.where(low).isEmpty():  # the threshold neither peels nor grows
            return out.unionAll(deg.select("v", F.lit(i).alias("level")))
        out = out.unionAll(deg.where(low).select("v", F.lit(i).alias("level")))
        stay = deg.where(~low).select("v")
        now = materialize(now.join(stay.withColumnRenamed("v", "src"), "src", "left_semi").join(stay.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst"))
        i += 1


def explain_choice(edges: DataFrame) -> DataFrame:
    """One row: sizes and the method triangles() takes."""
    f = facts(edges)
    how = "degree order" if f.most <= 64 * max(1.0, f.mean) else "peeling levels, then degree"
    return edges.sparkSession.createDataFrame([(f.n, f.m, f.most, f.wedges, how)], "n long, m long, max_degree long, square_sum long, method string")


def check(edges: DataFrame) -> bool:
    """Do the exact paths agree on this graph."""
    got = {triangles(edges).first()[0], triangles(edges, Rules(rank_triangles=False)).first()[0], baselines.brute(edges).first()[0]}
    return len(got) == 1
