"""Cost and accuracy measures."""

from __future__ import annotations

import math
import re
import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import degrees
from . import peel


def iterations(trace: DataFrame) -> DataFrame:
    return trace.agg(F.count("*").alias("iterations"))


def rounds_of(size: int, space: float) -> int:
    """Rounds of one pass over N = messages + 2 edges: send, sort, tree up and down; one if it fits."""
    if size <= space:
        return 1
    up = math.ceil(math.log(max(2, size)) / math.log(max(2.0, space)))
    tree = 2 * math.ceil(math.log(max(2, size)) / math.log(max(2.0, space / 2)))
    return 1 + up + tree


def model_rounds(trace: DataFrame, spaces: dict[str, float]) -> DataFrame:
    """space, rounds: the model's rounds summed over passes, for each space per machine."""
    big = (F.col("messages") + 2 * F.col("edges")).cast("double")
    out = None
    for name, s in spaces.items():
        s = max(2.0, float(s))
        up = F.ceil(F.round(F.ln(F.greatest(big, F.lit(2.0))) / math.log(s), 9))
        tree = 2 * F.ceil(F.round(F.ln(F.greatest(big, F.lit(2.0))) / math.log(max(2.0, s / 2)), 9))
        each = F.when(big <= s, F.lit(1)).otherwise(1 + up + tree)
        here = trace.agg(F.coalesce(F.sum(each), F.lit(0)).cast("long").alias("rounds")).select(F.lit(name).alias("space"), "rounds")
        out = here if out is None else out.unionAll(here)
    return out


def space(n: int, m: int, delta: float, mode: str = "nodes") -> int:
    """Space per machine: n^delta vertices, or 2 m^delta ln n edges."""
    return int(n**delta) if mode == "nodes" else int(2 * m**delta * math.log(max(2, n)))


def total_space(trace: DataFrame) -> DataFrame:
    """words: messages of all passes and both directions of the edges; cap: 2 m ln m."""
    m = F.max("edges")
    return trace.agg((F.sum("messages") + 2 * m).alias("words"), F.round(2 * m * F.ln(m), 6).alias("cap"))


def decay(trace: DataFrame) -> DataFrame:
    """Vertices and edges before each pass against n / 2^(2 (1.5^i - 1)) and m / 2^(2 (1.5^(i-1) - 1))."""
    first = trace.agg(F.max("vertices").alias("n"), F.max("edges").alias("m"))
    shrink = lambda i: F.pow(F.lit(2.0), 2 * (F.pow(F.lit(1.5), i) - 1))
    i = F.col("round").cast("double")
    t = trace.join(F.broadcast(first)).select(
        "round", "vertices", "edges", (F.col("n") / shrink(i)).alias("v_bound"), F.when(F.col("round") > 0, F.col("m") / shrink(i - 1)).otherwise(F.col("m").cast("double")).alias("e_bound")
    )
    return t.select("round", "vertices", "edges", (F.col("vertices") <= F.col("v_bound") + 1e-6).alias("vertices_ok"), (F.col("edges") <= F.col("e_bound") + 1e-6).alias("edges_ok"))


def message_bound(trace: DataFrame) -> DataFrame:
    """Messages of each pass against 2 m_i gamma_i."""
    b = 2 * F.col("edges") * F.col("gamma")
    return trace.select("round", "messages", (F.col("messages") <= b + 1e-6).alias("within"))


def factor(estimates: DataFrame, exact: DataFrame, col: str = "estimate") -> DataFrame:
    """estimate over truth."""
    t = exact.select(F.col(exact.columns[0]).alias("truth"))
    return estimates.join(F.broadcast(t)).withColumn("factor", F.when(F.col("truth") > 0, F.round(F.col(col) / F.col("truth"), 6)))


def coverage(estimates: DataFrame, truth: int, eps: float) -> DataFrame:
    """Mean relative error and the share of estimates within eps of the truth."""
    err = F.abs(F.col("estimate") - truth) / truth
    return estimates.agg(F.count("*").alias("runs"), F.round(F.avg(err), 6).alias("mean_error"), F.round(F.avg((err <= eps).cast("double")), 6).alias("coverage"))


def alb(edges: DataFrame, space_: int) -> DataFrame:
    """Least triangle numbers that guarantees ask for: sqrt(m/S), mean degree, sum of squared degrees."""
    d = degrees(edges).agg(F.count("*").alias("n"), (F.sum("deg") / 2).alias("m"), F.sum(F.col("deg") * F.col("deg")).alias("square_sum"))
    return d.select(F.round(F.sqrt(F.col("m") / space_), 6).alias("root_m_over_s"), F.round(2 * F.col("m") / F.col("n"), 6).alias("mean_degree"), "square_sum")


def load(profile: DataFrame) -> DataFrame:
    """From approx.load_profile: samples with edges, most edges, overflowed, light edges within 3/4 S, heavy within S/8."""
    heavy = F.col("edges") - F.col("light_edges")
    return profile.agg(
        F.count("*").alias("nonempty"),
        F.max("edges").alias("most_edges"),
        F.count_if(F.col("edges") > F.col("space")).alias("overflowed"),
        F.count_if(F.col("light_edges") * 4 > 3 * F.col("space")).alias("light_over"),
        F.count_if(heavy * 8 > F.col("space")).alias("heavy_over"),
    )


def sent(copies: DataFrame, p) -> DataFrame:
    """From approx.copies_per_edge: mean and most copies of an edge, and the mean over S M / m."""
    c = copies.agg((F.sum(F.col("copies") * F.col("edges")) / F.sum("edges")).alias("mean"), F.max("copies").alias("most"))
    return c.select(F.round("mean", 6).alias("mean"), "most", F.round(F.col("mean") / (p.space * p.machines / p.m), 6).alias("over_fair_share"))


def theory(p, triangles: int) -> dict[str, float]:
    """Expected hits, the variance bound of one sample and the bound on missing (1 +- eps)."""
    hits = p.p**3 * triangles * p.machines
    return {"expected_hits": hits, "sample_variance": p.p**3 * triangles + p.p**4 * triangles**2, "chebyshev": min(1.0, 2 / (p.eps**2 * p.p**2 * p.machines))}


def theory_row(spark, p, triangles: int) -> DataFrame:
    t = theory(p, triangles)
    return spark.createDataFrame([tuple(round(x, 6) for x in t.values())], ", ".join(f"{k} double" for k in t))


def copies(tree_rows: DataFrame, m: int, degeneracy: int, t: int) -> DataFrame:
    """Tree copies listed against m d^(t-2)."""
    return tree_rows.agg(F.count("*").alias("listed")).select("listed", (F.col("listed") <= m * degeneracy ** max(0, t - 2)).alias("within"))


def plan_stats(df: DataFrame) -> dict[str, int]:
    """Exchanges, joins by kind and Python nodes of the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda p: len(re.findall(p, text))
    return {
        "exchanges": count(r"\bExchange (?:hash|range|Round|Single)"),
        "broadcasts": count(r"BroadcastExchange"),
        "merge_joins": count(r"SortMergeJoin"),
        "nested_loops": count(r"BroadcastNestedLoopJoin|CartesianProduct"),
        "python": count(r"Python|Pandas|Arrow"),
    }


def run_cost(df: DataFrame) -> dict[str, float]:
    """Run df into nothing: seconds, tasks, bytes shuffled and spilled of its stages, beside plan_stats()."""
    sc = df.sparkSession.sparkContext
    store, none = sc._jsc.sc().statusStore(), sc._jvm.java.util.ArrayList()
    quantiles = sc._gateway.new_array(sc._jvm.double, 0)

    def stages():
        found = store.stageList(None, False, False, quantiles, none)
        return [found.apply(i) for i in range(found.size())]

    before = max((s.stageId() for s in stages()), default=-1)
    t = time.time()
    df.write.mode("overwrite").format("noop").save()
    took = time.time() - t
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    own = [s for s in stages() if s.stageId() > before]
    total = lambda f: sum(getattr(s, f)() for s in own)
    return {
        "seconds": round(took, 3),
        "tasks": total("numCompleteTasks"),
        "shuffle_written": total("shuffleWriteBytes"),
        "shuffle_read": total("shuffleReadBytes"),
        "spilled": total("memoryBytesSpilled") + total("diskBytesSpilled"),
        **plan_stats(df),
    }


def cost_table(spark, runs: dict[str, DataFrame]) -> DataFrame:
    """method, seconds, tasks, bytes shuffled and spilled, exchanges and joins of each."""
    rows = [(name, *run_cost(df).values()) for name, df in runs.items()]
    kinds = "seconds double, tasks long, shuffle_written long, shuffle_read long, spilled long, exchanges int, broadcasts int, merge_joins int, nested_loops int, python int"
    return spark.createDataFrame(rows, f"method string, {kinds}")


def spaces(spark, n: int, m: int) -> DataFrame:
    """mode, delta, space: machine spaces in vertices (n^delta) and in edges (2 m^delta ln n)."""
    rows = [(mode, x, space(n, m, x, mode)) for mode, ds in (("nodes", (0.3, 0.5, 0.9)), ("edges", (0.5, 0.75))) for x in ds]
    return spark.createDataFrame(rows, "mode string, delta double, space long")


def trace_of(edges: DataFrame, gamma: peel.Schedule) -> DataFrame:
    return peel.trace_table(edges.sparkSession, peel.rounds(edges, gamma))
