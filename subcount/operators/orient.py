"""Acyclic orientations of small out-degree, and degeneracy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import arcs, size
from ..session import ship
from ..storage import forget, materialize
from . import blocks, cores, exact, peel

LOCAL_ARCS = 80_000_000  # survivors of so few arcs are finished by one task, which holds 4 bytes an arc and their packed edges
SLICE = 1 << 19  # edges put into the lists at once
WAVES = "v long, wave int, core long"


def _lists(chunks) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, and start and near: the neighbours near[start[i] : start[i + 1]] of vertex i. chunks: a function that gives
    src and dst of some edges at a time; it is called three times, so that only one chunk is held besides."""
    ids = np.empty(0, np.int64)
    for ends in chunks():
        ids = np.union1d(ids, np.concatenate(ends))
    numbered = lambda: ([np.searchsorted(ids, x).astype(np.int32) for x in ends] for ends in chunks())
    size = np.zeros(len(ids), np.int64)
    for x, y in numbered():
        size += np.bincount(x, minlength=len(ids)) + np.bincount(y, minlength=len(ids))
    start = np.concatenate([[0], np.cumsum(size)])
    free, near = start[:-1].copy(), np.empty(start[-1], np.int32)
    for x, y in ((x[s : s + SLICE], y[s : s + SLICE]) for x, y in numbered() for s in range(0, len(x), SLICE)):
        tail, head = np.concatenate([x, y]), np.concatenate([y, x])
        order = np.argsort(tail, kind="stable")
        each = np.bincount(tail, minlength=len(ids))
        near[np.arange(len(tail)) + np.repeat(free - np.cumsum(each) + each, each)] = head[order]
        free += each
    return ids, start, near


def _peeled(ids: np.ndarray, start: np.ndarray, near: np.ndarray, k: int, wave: int):
    """The same waves of least degree in memory: v, wave, core of each. Only the neighbours of what goes are looked at."""
    deg, here = np.diff(start), np.ones(len(ids), bool)
    while True:
        left = np.flatnonzero(here & (deg > 0))
        if not len(left):
            return
        k = max(k, int(deg[left].min()))
        low = left[deg[left] <= k]
        while len(low):
            yield ids[low], wave, k
            here[low], each = False, start[low + 1] - start[low]
            hit = near[np.arange(int(each.sum())) + np.repeat(start[low] - np.cumsum(each) + each, each)]
            hit, times = np.unique(hit[here[hit]], return_counts=True)
            deg[hit] -= times
            wave, low = wave + 1, hit[(deg[hit] > 0) & (deg[hit] <= k)]


def _finished(edges: DataFrame, k: int, wave: int) -> DataFrame:
    """(v, wave, core) by one task, which is handed the edges packed."""

    def run(group: pa.Table) -> pa.Table:
        rows = [(group["src"][i].as_py, group["dst"][i].as_py, group["n"][i].as_py()) for i in range(group.num_rows)]
        found = list(_peeled(*_lists(lambda: ((blocks._swell(src(), n), blocks._swell(dst(), n)) for src, dst, n in rows)), k, wave))
        v = np.concatenate([x for x, _, _ in found]) if found else np.empty(0, np.int64)
        times = [len(x) for x, _, _ in found]
        column = lambda i, kind: np.repeat(np.array([x[i] for x in found], kind), times)
        return pa.table({"v": v, "wave": column(1, np.int32), "core": column(2, np.int64)})

    ship(edges.sparkSession)
    return materialize(blocks.packed(edges, 1).groupBy("a").applyInArrow(run, WAVES))


def _rounds(start: np.ndarray, near: np.ndarray, gamma: peel.Schedule):
    """number, gamma, n, edges, peeled, messages of the rounds of peel.rounds, in memory."""
    deg, i = np.diff(start), 0
    while True:
        g, left = gamma(i), np.flatnonzero(deg)
        low = left[deg[left] <= g]
        if not len(left) or not len(low) and gamma(i + 1) <= g:
            return
        yield i, g, len(left), int(deg[left].sum()) // 2, len(low), int((deg[low] ** 2).sum())
        gone = np.zeros(len(deg), bool)
        gone[low], each = True, start[low + 1] - start[low]
        ends, s = np.cumsum(each), 0
        while s < len(low):
            e = max(s + 1, int(np.searchsorted(ends, (ends[s - 1] if s else 0) + 8 * SLICE, "right")))
            part, times = low[s:e], each[s:e]
            hit = near[np.arange(int(times.sum())) + np.repeat(start[part] - np.cumsum(times) + times, times)]
            deg -= np.bincount(hit, minlength=len(deg))  # those that went before fall under 0 and are put back
            s = e
        deg[gone] = 0
        np.maximum(deg, 0, out=deg)
        i += 1


def traces(edges: DataFrame, schedules: list[tuple[str, float]], most: int = LOCAL_ARCS) -> list[list[tuple]]:
    """number, gamma, n, edges, peeled, messages of each round, by schedule (kind and start bound). Of a graph of at most
    `most` arcs one task a schedule goes through the rounds and is handed the edges packed; a larger one is peeled in
    written tables, one schedule after the other, and a round's tables go with it. edges: best a written table."""
    if 2 * edges.count() > most:
        return [[(r.number, r.gamma, r.n, r.edges, r.peeled, r.messages) for r in peel.rounds(edges, peel.schedule(*s), keep=False).rounds] for s in schedules]

    def run(key: tuple, group: pa.Table) -> pa.Table:
        rows = [(group["src"][i].as_py, group["dst"][i].as_py, group["n"][i].as_py()) for i in range(group.num_rows)]
        _, start, near = _lists(lambda: ((blocks._swell(src(), n), blocks._swell(dst(), n)) for src, dst, n in rows))
        found = list(_rounds(start, near, peel.schedule(*schedules[key[0].as_py()])))
        column = lambda i, kind: pa.array([x[i] for x in found], kind)
        kinds = (pa.int32(), pa.float64(), *[pa.int64()] * 4)
        return pa.table({"s": pa.array([key[0].as_py()] * len(found), pa.int32()), **{n: column(i, k) for i, (n, k) in enumerate(zip(("number", "gamma", "n", "edges", "peeled", "messages"), kinds))}})

    ship(edges.sparkSession)
    dealt = blocks.packed(edges, 1).withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(len(schedules) - 1))))
    kind = "s int, number int, gamma double, n long, edges long, peeled long, messages long"
    found = dealt.repartition(len(schedules), "s").groupBy("s").applyInArrow(run, kind).collect() if schedules else []
    return [[tuple(r)[1:] for r in sorted(found) if r["s"] == s] for s in range(len(schedules))]


def waves(edges: DataFrame, factor: float | None = None) -> tuple[DataFrame, int]:
    """(v, wave, core) and the largest core. Without a factor: waves of least degree (exact degeneracy); with
    one: waves of degree at most factor times the survivors' mean degree, O(log n) of them. edges: best a written table."""
    k, wave, out, now = 0, 0, None, None
    if factor is None and 2 * edges.count() <= LOCAL_ARCS:
        out = _finished(edges, k, wave)
        return out, out.agg(F.coalesce(F.max("core"), F.lit(0))).first()[0]
    now = materialize(arcs(edges))
    while True:
        deg = materialize(now.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")))
        n, least, total = deg.agg(F.count("*"), F.min("deg"), F.sum("deg")).first()
        if not n:
            return out if out is not None else edges.sparkSession.createDataFrame([], WAVES), k
        if factor is None and total <= LOCAL_ARCS:
            here = _finished(now.where("src < dst"), k, wave)
            return here if out is None else out.unionAll(here), here.agg(F.max("core")).first()[0]
        k = max(k, least) if factor is None else max(k, int(factor * total / n))
        bound = k if factor is None else max(least, factor * total / n)
        here = deg.where(F.col("deg") <= bound).select("v", F.lit(wave).alias("wave"), F.lit(k).cast("long").alias("core"))
        out = here if out is None else out.unionAll(here)
        stay = deg.where(F.col("deg") > bound).select("v")
        was, now = now, materialize(
            now.join(stay.withColumnRenamed("v", "src"), "src", "left_semi").join(stay.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")
        )
        forget(was)
        wave += 1


def degeneracy(edges: DataFrame) -> DataFrame:
    """One row: degeneracy. Of a graph of over LOCAL_ARCS arcs by bounds of the core numbers, without a table for each wave."""
    m, value = edges.count(), None
    if 2 * m > LOCAL_ARCS:
        value = cores.degeneracy(edges, m, LOCAL_ARCS, lambda inner: _finished(inner, 0, 0).agg(F.max("core")).first()[0])
    if value is None:
        value = waves(edges)[1]
    return edges.sparkSession.createDataFrame([(int(value),)], "degeneracy long")


def low_outdegree(edges: DataFrame, how: str = "degree", epsilon: float = 0.5) -> DataFrame:
    """src -> dst, acyclic. degree: by (degree, id), no loop; peel: by waves at (2 + epsilon) times the mean
    degree; degeneracy: by waves of least degree."""
    if how == "degree":
        e = exact.ranked(edges)
    elif how in ("peel", "degeneracy"):
        w = waves(edges, 2 + epsilon if how == "peel" else None)[0]
        e = exact.ranked(edges, w.select("v", F.col("wave").alias("level")))
    else:
        raise ValueError(f"how is degree, peel or degeneracy, not {how}")
    return e.select(F.col("u").alias("src"), F.col("v").alias("dst"))


def by_levels(edges: DataFrame, gamma: peel.Schedule) -> DataFrame:
    e = exact.ranked(edges, peel.levels(edges, gamma))
    return e.select(F.col("u").alias("src"), F.col("v").alias("dst"))


def sparsity(edges: DataFrame) -> DataFrame:
    """n, m, degeneracy, largest out-degrees of both orders, and the bracket of the arboricity."""
    w, d = waves(edges)
    best = lambda o: o.groupBy("src").count().agg(F.coalesce(F.max("count"), F.lit(0)))
    out = low_outdegree(edges)
    deg = exact.ranked(edges, w.select("v", F.col("wave").alias("level"))).select(F.col("u").alias("src"), F.col("v").alias("dst"))
    a, b = best(out).toDF("outdegree_by_degree"), best(deg).toDF("outdegree_by_core")
    low = F.when(F.col("n") > 1, F.ceil(F.col("m") / (F.col("n") - 1))).otherwise(0).alias("arboricity_low")
    return size(edges).join(F.broadcast(a)).join(F.broadcast(b)).select("n", "m", F.lit(int(d)).cast("long").alias("degeneracy"), "outdegree_by_degree", "outdegree_by_core", low, F.lit(int(d)).cast("long").alias("arboricity_high"))
