"""Exact top-k search by inner product: columnar branch and bound.

Vectors are whole numbers, floor(256 x). Rows are laid out by dimension. For a chunk of queries the inner
products grow one block of dimensions at a time; after a block, a row can still reach at most its partial
sum plus the product of the norms of what remains. Pairs whose bound is under the query's fifth best score
so far are dropped, and once few are left the survivors are compacted to lists and only they go on.

Queries are sent in blocks of about `block` vectors, a stated size, and each block makes one pass over
the rows; a task keeps k rows per query of the block, whatever the number of rows it reads. With several blocks
each is collected, sent, searched and its result written before the next, so the driver and the tasks hold one.

Defined cases: vectors that are null, empty or hold null or non-finite values take no part; rows of
another length than the query's are not compared; ties take the smaller vec_id; candidate rows that repeat a
vec_id count each; rows of the query's own vec_id are no candidates; query rows that repeat an id and a vector are
one query, those of one id and different vectors are queries of their own with k rows each; fewer than k
candidates are all returned; null ids take no part; without queries or rows there is no result; further columns
are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_columns, materialize

K, BLOCK, STRIDE, SCALE = 5, 50_000, 16, 256
ROWS_AT_ONCE = 4096
SCHEMA = "query long, query_id long, vec_id long, score long"


def quantized(vectors: list, dims: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(positions that take part, their floor(256 x) rows as float64), of vectors of one length."""
    keep, rows = [], []
    for i, v in enumerate(vectors):
        if v and (dims is None or len(v) == dims) and None not in v:
            keep.append(i)
            rows.append(v)
    if not rows:
        return np.empty(0, int), np.empty((0, dims or 0))
    x = np.floor(SCALE * np.array(rows, np.float64))
    fine = np.isfinite(x).all(1)
    return np.array(keep)[fine], x[fine]


def remaining(x: np.ndarray, stride: int) -> np.ndarray:
    """Norms of the dimensions from each block's start on: rows x (blocks + 1)."""
    squares = np.add.reduceat(x * x, np.arange(0, x.shape[1], stride), 1)
    return np.sqrt(np.hstack([np.cumsum(squares[:, ::-1], 1)[:, ::-1], np.zeros((len(x), 1))]))


class Search:
    """The best rows of a block of queries over all rows a task sees."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, k: int, stride: int = STRIDE):
        self.ids, self.q, self.k, self.stride = ids, queries, k, stride
        self.mass = remaining(queries, stride)
        self.best = [[np.empty(0, np.int64), np.empty(0)] for _ in ids]  # vec_ids, scores
        self.floor = np.full(len(ids), -np.inf)
        self.big = np.abs(queries).max(initial=0)

    def add(self, ids: np.ndarray, x: np.ndarray, chunk: int = 256) -> None:
        if self.big * np.abs(x).max(initial=0) * x.shape[1] >= 2**53:
            return self.add_large(ids, x)
        mass, columns = remaining(x, self.stride), np.ascontiguousarray(x.T)
        dims = x.shape[1]
        for a in range(0, len(self.ids), chunk):
            q, floor = self.q[a : a + chunk], self.floor[a : a + chunk]
            part, d, block, lists = np.zeros((len(q), len(x))), 0, 0, None
            while d < dims:
                end = min(dims, d + self.stride)
                if lists is None:
                    part += q[:, d:end] @ columns[d:end]
                else:
                    r, c = lists
                    part += np.einsum("pd,pd->p", q[r, d:end], x[c, d:end])
                d, block = end, block + 1
                if lists is None:
                    bound = part + self.mass[a : a + chunk, [block]] * mass[:, block] * (1 + 1e-12) + 1e-6
                    alive = bound >= floor[:, None]
                    if d >= dims or np.count_nonzero(alive) * 8 < alive.size:
                        lists = np.nonzero(alive)
                        part = part[lists]
                elif d < dims:
                    r, c = lists
                    alive = part + self.mass[a + r, block] * mass[c, block] * (1 + 1e-12) + 1e-6 >= floor[r]
                    lists, part = (r[alive], c[alive]), part[alive]
            self._keep(a, *lists, part, ids)

    def add_large(self, ids, x):
        """Whole numbers beyond double precision: the same products on Python integers."""
        q, v = self.q.astype(object), x.astype(object)
        to_int = np.vectorize(int, otypes=[object])
        part = to_int(q) @ to_int(v).T
        for a in range(len(q)):
            self._keep(a, np.zeros(len(x), int), np.arange(len(x)), part[a], ids)

    def _keep(self, a, r, c, scores, ids):
        order = np.argsort(r, kind="stable")
        r, c, scores = r[order], c[order], scores[order]
        starts = np.flatnonzero(np.diff(r, prepend=-1))
        for s, e in zip(starts, np.append(starts[1:], len(r))):
            at = a + int(r[s])
            v, w = ids[c[s:e]], scores[s:e]
            other = (v != self.ids[at]) & (w >= self.floor[at])
            if not other.any():
                continue
            v, w = np.concatenate([self.best[at][0], v[other]]), np.concatenate([self.best[at][1], w[other]])
            top = np.lexsort((v, -w))[: self.k]
            self.best[at] = [v[top], w[top]]
            if len(top) == self.k:
                self.floor[at] = w[top[-1]]

    def rows(self, first: int) -> dict[str, list]:
        """The best rows; queries are numbered from first."""
        out: dict[str, list] = {"query": [], "query_id": [], "vec_id": [], "score": []}
        for number, (q, (v, w)) in enumerate(zip(self.ids, self.best), first):
            out["query"] += [number] * len(v)
            out["query_id"] += [int(q)] * len(v)
            out["vec_id"] += v.tolist()
            out["score"] += [int(s) for s in w]
        return out


def distinct(ids: list, vectors: list, dims: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and whole-number vectors of the queries of one length, each pair once, in their order."""
    keep, x = quantized(vectors, dims)
    ids = np.array(ids, np.int64)[keep] if len(keep) else np.empty(0, np.int64)
    seen = dict.fromkeys((int(i), v.tobytes()) for i, v in zip(ids, x))
    order = sorted(seen)
    return np.array([i for i, _ in order], np.int64), np.array([np.frombuffer(v) for _, v in order]).reshape(len(order), dims)


def search(vectors: DataFrame, queries: DataFrame, k: int = K, block: int = BLOCK, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score for each query; queries has the same columns as vectors."""
    spark = vectors.sparkSession
    take = [F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("v")]
    given = vectors.select(*take).where("id is not null and v is not null")
    asked = queries.select(*take).where("id is not null and v is not null")
    parts = max(1, -(-asked.count() // block))
    found = None
    for part in range(parts):
        some = asked if parts == 1 else asked.where(F.pmod(F.xxhash64("id"), F.lit(parts)) == part)
        rows = some.toArrow().to_pydict()
        by_dims = {d: distinct(rows["id"], rows["v"], d) for d in sorted({len(v) for v in rows["v"] if v})}
        shared = spark.sparkContext.broadcast(by_dims)

        def make(shared=shared, part=part):
            searches = {d: Search(ids, x, k) for d, (ids, x) in shared.value.items() if len(ids)}

            class Step:
                def __call__(self, cols):
                    ids, v = cols["id"], cols["v"]
                    for s in range(0, len(ids), ROWS_AT_ONCE):
                        for dims, one in searches.items():
                            keep, x = quantized(v[s : s + ROWS_AT_ONCE], dims)
                            if len(keep):
                                one.add(np.array(ids[s : s + ROWS_AT_ONCE], np.int64)[keep], x)
                    return iter(())

                def finish(self):
                    first = part << 32
                    for one in searches.values():
                        yield one.rows(first)
                        first += len(one.ids)

            return Step()

        here = map_columns(given, ["id", "v"], SCHEMA, make)
        if parts > 1:
            here = materialize(best(here, k))
            shared.destroy()
        found = here if found is None else found.unionByName(here)
    return best(found, k).select("query_id", "rank", "vec_id", "score")


def best(found: DataFrame, k: int) -> DataFrame:
    """The k best rows of each query number, ranked."""
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k)
