"""The degeneracy of a graph that is too large for one task.

Every vertex has a bound of its core number, its degree at first. A round lowers it to the largest h such that h of its
neighbours have a bound of h at least; what no round lowers are the core numbers. The neighbours' lists are dealt once, to
parts by a hash, and written packed; a round reads them again beside the bounds, so that only bounds are shuffled. No
graph has fewer edges a vertex than its degeneracy allows, so the vertices of a bound under the greatest mean are not in
the innermost core, and once the rest fits one task, it is finished there.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from ..storage import forget, materialize
from . import blocks

PART_ARCS = 8_000_000  # of the lists that a task holds
MOST_VERTICES = 10_000_000  # whose bounds a task is handed
SWEEPS = 8  # of a part in a round, with the bounds of the other parts as they were
WAIT = 8  # rounds in which the rest is made a quarter of what fits one task
CHUNK = 1 << 21  # arcs looked at once
_LISTS = "tail binary, size binary, near binary, k long, n long"
_BOUNDS = "bound binary, n long, changed long, most long, floor long, arcs long"


def _segments(start: np.ndarray):
    """Ranges of vertices with about CHUNK arcs."""
    s, n = 0, len(start) - 1
    while s < n:
        e = max(s + 1, int(np.searchsorted(start, start[s] + CHUNK, "right")) - 1)
        yield s, e
        s = e


def lowered(own: np.ndarray, start: np.ndarray, near: np.ndarray, bound: np.ndarray) -> bool:
    """One sweep over the vertices `own` (at least one arc each) with lists near[start[i] : start[i + 1]]; bounds are changed in place."""
    changed = False
    for s, e in _segments(start):
        at, size = start[s:e] - start[s], np.diff(start[s : e + 1])
        mine, theirs = bound[own[s:e]], bound[near[start[s] : start[e]]]
        low = np.add.reduceat(theirs >= np.repeat(mine, size), at, dtype=np.int64) < mine
        if not low.any():
            continue
        changed, here = True, np.repeat(low, size)
        mine, size, theirs = mine[low].astype(np.int64), size[low], theirs[here]
        off = np.concatenate([[0], np.cumsum(mine + 1)])
        times = np.bincount(np.repeat(off[:-1], size) + np.minimum(theirs, np.repeat(mine, size)), minlength=off[-1])
        least = np.concatenate([np.cumsum(times[::-1])[::-1], [0]])  # how many from here on
        each = mine + 1
        enough = least[:-1] - np.repeat(least[off[1:]], each) >= np.arange(off[-1]) - np.repeat(off[:-1], each)
        bound[own[s:e][low]] = np.add.reduceat(enough, off[:-1], dtype=np.int64) - 1
    return changed


def _lists(edges: DataFrame, parts: int) -> DataFrame:
    """tail, size, near, k, n of each part: its vertices, their numbers of neighbours and these, packed, and how many."""

    def run(key: tuple, group: pa.Table) -> pa.Table:
        src, dst = blocks._ends(group)
        a, b = (blocks.colour(x, parts) == key[0].as_py() for x in (src, dst))
        tail, near = np.concatenate([src[a], dst[b]]), np.concatenate([dst[a], src[b]])
        del src, dst, a, b
        order = np.lexsort((near, tail))
        tail, near = tail[order], near[order]
        del order
        first = np.flatnonzero(np.concatenate([[True], tail[1:] != tail[:-1]]))
        size = np.diff(np.concatenate([first, [len(tail)]]))
        return pa.table({"tail": [blocks._squeeze(tail[first])], "size": [blocks._squeeze(size)], "near": [blocks._squeeze(near)], "k": [len(first)], "n": [len(tail)]}, schema=_schema(_LISTS))

    dealt = blocks.packed(edges, parts).withColumn("part", F.explode(F.array_distinct(F.array("a", "b"))))
    return materialize(dealt.select("part", "n", "src", "dst").repartition(min(parts, 2000), "part").groupBy("part").applyInArrow(run, _LISTS))


def _schema(ddl: str) -> pa.Schema:
    kinds = {"binary": pa.binary(), "long": pa.int64()}
    return pa.schema([(x.split()[0], kinds[x.split()[1]]) for x in ddl.split(", ")])


def _numbered(lists: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The lists with vertices by their places in the order of ids, and the bounds to begin with."""

    def places(group: pa.Table) -> pa.Table:
        tail, size = (np.concatenate([blocks._swell(x.as_py(), k) for x, k in zip(group[c], group["k"].to_pylist())]) for c in ("tail", "size"))
        order = np.argsort(tail)
        return pa.table({"ids": [blocks._squeeze(tail[order])], "bound": [blocks._squeeze(size[order])], "total": [len(tail)]}, schema=_schema("ids binary, bound binary, total long"))

    known = materialize(lists.select("tail", "size", "k").withColumn("all", F.lit(0)).groupBy("all").applyInArrow(places, "ids binary, bound binary, total long"))

    def run(batches):
        for batch in batches:
            for tail, size, near, k, n, ids, total in zip(*(batch[c] for c in ("tail", "size", "near", "k", "n", "ids", "total"))):
                k, n, ids = k.as_py(), n.as_py(), blocks._swell(ids.as_py(), total.as_py())
                place = lambda x, m: blocks._squeeze(np.searchsorted(ids, blocks._swell(x.as_py(), m)))
                yield pa.RecordBatch.from_pydict({"tail": [place(tail, k)], "size": [size.as_py()], "near": [place(near, n)], "k": [k], "n": [n]}, schema=_schema(_LISTS))

    numbered = materialize(lists.crossJoin(known.select("ids", "total")).mapInArrow(run, _LISTS))
    first = known.select("bound", F.col("total").alias("n"))
    return numbered, first


def _held(batch):
    """own, start, near, bound of each part."""
    for tail, size, near, k, n, bound, total in zip(*(batch[c] for c in ("tail", "size", "near", "k", "n", "bound", "total"))):
        k, n = k.as_py(), n.as_py()
        start = np.concatenate([[0], np.cumsum(blocks._swell(size.as_py(), k))])
        yield blocks._swell(tail.as_py(), k), start, blocks._swell(near.as_py(), n).astype(np.int32), blocks._swell(bound.as_py(), total.as_py()).astype(np.int32)


def _round(lists: DataFrame, bounds: DataFrame) -> DataFrame:
    """The bounds after a round, and of those before it: how many were lowered, the greatest mean of edges a vertex among the
    vertices of some bound or a higher one (floor), and the arcs between vertices whose bounds are that at least."""
    found = "tail binary, bound binary, k long, changed long, arcs binary, vertices binary, high long, total long"

    def run(batches):
        for batch in batches:
            for own, start, near, bound in _held(batch):
                before, high = bound[own], int(bound.max()) + 1
                arcs, vertices = np.zeros(high, np.int64), np.bincount(before, minlength=high)
                for s, e in _segments(start):
                    both = np.minimum(np.repeat(before[s:e], np.diff(start[s : e + 1])), bound[near[start[s] : start[e]]])
                    arcs += np.bincount(both, minlength=high)
                for _ in range(SWEEPS):
                    if not lowered(own, start, near, bound):
                        break
                packed = {"tail": own, "bound": bound[own].astype(np.int64), "arcs": arcs, "vertices": vertices}
                counts = {"k": len(own), "changed": int((bound[own] < before).sum()), "high": high, "total": len(bound)}
                yield pa.RecordBatch.from_pydict({x: [blocks._squeeze(y)] for x, y in packed.items()} | {x: [y] for x, y in counts.items()}, schema=_schema(found))

    def meet(group: pa.Table) -> pa.Table:
        total, high = group["total"][0].as_py(), group["high"][0].as_py()
        bound, arcs, vertices = np.zeros(total, np.int64), np.zeros(high, np.int64), np.zeros(high, np.int64)
        for tail, new, k, each, of in zip(*(group[c] for c in ("tail", "bound", "k", "arcs", "vertices"))):
            bound[blocks._swell(tail.as_py(), k.as_py())] = blocks._swell(new.as_py(), k.as_py())
            arcs += blocks._swell(each.as_py(), high)
            vertices += blocks._swell(of.as_py(), high)
        arcs, vertices = (np.cumsum(x[::-1])[::-1] for x in (arcs, vertices))
        floor = int((-(-arcs // (2 * np.maximum(vertices, 1)))).max())
        row = {"n": [total], "changed": [sum(group["changed"].to_pylist())], "most": [int(bound.max())], "floor": [floor], "arcs": [int(arcs[floor])]}
        return pa.table({"bound": [blocks._squeeze(bound)]} | row, schema=_schema(_BOUNDS))

    parts = lists.crossJoin(bounds.select("bound", F.col("n").alias("total"))).mapInArrow(run, found)
    return materialize(parts.withColumn("all", F.lit(0)).groupBy("all").applyInArrow(meet, _BOUNDS))


def _inner(lists: DataFrame, bounds: DataFrame, floor: int) -> DataFrame:
    """n, src, dst: the packed edges between vertices whose bounds are `floor` at least."""
    kind = "n long, src binary, dst binary"

    def run(batches):
        for batch in batches:
            for own, start, near, bound in _held(batch):
                for s, e in _segments(start):
                    src, dst = np.repeat(own[s:e], np.diff(start[s : e + 1])), near[start[s] : start[e]]
                    stay = (src < dst) & (bound[src] >= floor) & (bound[dst] >= floor)
                    src, dst = src[stay], dst[stay].astype(np.int64)
                    yield pa.RecordBatch.from_pydict({"n": [len(src)], "src": [blocks._squeeze(src)], "dst": [blocks._squeeze(dst)]}, schema=_schema(kind))

    return lists.crossJoin(bounds.select("bound", F.col("n").alias("total"))).mapInArrow(run, kind)


def degeneracy(edges: DataFrame, m: int, most: int, finished) -> int | None:
    """The largest core number of a graph of m > 0 edges; None where there are over MOST_VERTICES vertices. Once at most
    `most` arcs can be in the innermost core, finished(their edges, packed) gives it. edges: best a written table."""
    ship(edges.sparkSession)
    dealt = _lists(edges, max(1, math.ceil(2 * m / PART_ARCS)))
    if dealt.agg(F.sum("k")).first()[0] > MOST_VERTICES:
        forget(dealt)
        return None
    lists, bounds = _numbered(dealt)
    forget(dealt)
    wait = WAIT
    while True:
        after = _round(lists, bounds)
        changed, top, floor, arcs = after.select("changed", "most", "floor", "arcs").first()
        if not changed:
            return top
        if arcs <= (most // 4 if wait > 0 else most):
            return finished(_inner(lists, bounds, floor))
        if wait < WAIT:
            forget(bounds)
        bounds, wait = after, wait - 1
