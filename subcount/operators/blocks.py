"""Counting k-cliques (k = 3, 4) and the patterns of four vertices without a row for any wedge.

Vertices get one of c colours by a hash. A block is a multiset of k colours; an edge goes to the blocks that hold the
colours of both its ends, packed (sorted, differences, compressed) before it is dealt, and a block counts the cliques
whose colours are just its own, so every clique is counted in one block. Inside a block vertices are ordered by
degree, which bounds out-degrees by the root of twice its edges. What is shuffled is C(c + k - 3, k - 2) packed copies
of an edge, not wedges; c grows with the root of the edges over what a block may hold.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce
from itertools import combinations_with_replacement, permutations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import degrees, ends, numbers, renumbered
from ..session import ship
from ..storage import forget, materialize

BLOCK_EDGES = 8_000_000
WAVE_EDGES = 50_000_000  # packed copies of edges, or as many as edges, that are dealt before their shuffle files go
CELLS = 24  # colours by which the repeats of an edge meet
LINK_TRIANGLES = 4_000_000  # of a group in which links are counted
PACK_EDGES = 2_000_000  # edges that a task packs at once
ROWS = 1 << 18  # that a block sends at once
FEW = 1000  # values packed as they are
LEAST_COLOURS = 4  # so that small graphs are counted side by side
WEDGES, MARKS = 1 << 22, 1 << 25  # of a batch
_MIX = np.uint64(0x9E3779B97F4A7C15)


def colours_for(m: int, k: int = 3, block: int = BLOCK_EDGES) -> int:
    """Colours under which a block of k different ones holds about `block` edges at most."""
    return max(LEAST_COLOURS, math.ceil(math.sqrt(k * (k - 1) * m / block)))


def copies(c: int, k: int) -> int:
    """Blocks that an edge goes to."""
    return math.comb(c + k - 3, k - 2)


def colour(v: np.ndarray, c: int) -> np.ndarray:
    x = v.astype(np.int64).view(np.uint64) * _MIX
    x = (x ^ (x >> np.uint64(32))) * _MIX
    return ((x >> np.uint64(33)) % np.uint64(c)).astype(np.int64)


_ZSTD = b"\x28\xb5\x2f\xfd"  # with which the compressed bytes begin


def _squeeze(x: np.ndarray) -> bytes:
    """Differences by byte planes, compressed. Of long values that come often: the different ones and the places in them."""
    if len(x) >= FEW and x.max() >> 31:
        kinds, places = np.unique(x, return_inverse=True)
        if 4 * len(kinds) <= len(x):
            known = _squeezed(kinds)
            return b"".join((len(kinds).to_bytes(8, "little"), len(known).to_bytes(8, "little"), known, _squeezed(places.astype(np.int64))))
    return _squeezed(x)


def _squeezed(x: np.ndarray) -> bytes:
    d = np.diff(x, prepend=np.int64(0)).view(np.uint64)
    return pa.compress(np.ascontiguousarray(d.view(np.uint8).reshape(-1, 8).T).tobytes(), codec="zstd", asbytes=True)


def _swell(data: bytes, n: int) -> np.ndarray:
    if data[:4] != _ZSTD:
        kinds, known = (int.from_bytes(data[i : i + 8], "little") for i in (0, 8))
        return _swell(data[16 : 16 + known], kinds)[_swell(data[16 + known :], n)]
    planes = np.frombuffer(pa.decompress(data, 8 * n, codec="zstd", asbytes=True), np.uint8).reshape(8, n)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.int64).ravel())


def _in_order(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """By (src, dst), without repeats."""
    if len(src) and min(src.min(), dst.min()) >= 0 and max(src.max(), dst.max()) < 1 << 31:
        key = (src << 31) | dst
        key.sort()
        key = key[np.diff(key, prepend=-1) != 0]
        return key >> 31, key & ((1 << 31) - 1)
    order = np.lexsort((dst, src))
    src, dst = src[order], dst[order]
    new = np.ones(len(src), bool)
    new[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
    return src[new], dst[new]


PACKED = "a int, b int, n long, src binary, dst binary"
_PACKED = pa.schema([("a", pa.int32()), ("b", pa.int32()), ("n", pa.int64()), ("src", pa.binary()), ("dst", pa.binary())])


def _by_colours(src: np.ndarray, dst: np.ndarray, c: int):
    src, dst = _in_order(src, dst)
    a, b = colour(src, c), colour(dst, c)
    kind = np.minimum(a, b) * c + np.maximum(a, b)
    order = np.argsort(kind.astype(np.uint16) if c < 256 else kind, kind="stable")
    src, dst, kind = src[order], dst[order], kind[order]
    cuts = np.flatnonzero(np.diff(kind, prepend=-1))
    for s, e in zip(cuts, [*cuts[1:], len(kind)]):
        a, b = divmod(int(kind[s]), c)
        yield pa.RecordBatch.from_pydict({"a": [a], "b": [b], "n": [int(e - s)], "src": [_squeeze(src[s:e])], "dst": [_squeeze(dst[s:e])]}, schema=_PACKED)


def packed(edges: DataFrame, c: int) -> DataFrame:
    """a <= b, n, src, dst: edges by the colours of their ends, some of a task's in a row. edges: src and dst, or packed
    by other colours."""
    rows = "n" not in edges.columns

    def arrays(batch):
        if rows:
            yield batch["src"].to_numpy(), batch["dst"].to_numpy()
        else:
            for n, src, dst in zip(batch["n"].to_pylist(), batch["src"], batch["dst"]):
                yield _swell(src.as_py(), n), _swell(dst.as_py(), n)

    def run(batches):
        held, n = [], 0
        for batch in batches:
            for found in arrays(batch):
                held.append(found)
                n += len(found[0])
                if n >= PACK_EDGES:
                    yield from _by_colours(*map(np.concatenate, zip(*held)), c)
                    held, n = [], 0
        if n:
            yield from _by_colours(*map(np.concatenate, zip(*held)), c)

    ship(edges.sparkSession)
    read = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")) if rows else edges.select("n", "src", "dst")
    return read.mapInArrow(run, PACKED)


def _ends(group: pa.Table) -> list[np.ndarray]:
    n = group["n"].to_pylist()
    return [np.concatenate([_swell(x.as_py(), y) for x, y in zip(group[name], n)]) for name in ("src", "dst")]


def stored(pairs: DataFrame, c: int = CELLS) -> DataFrame:
    """The distinct edges of the pairs in a written packed table; null ends, loops and repeats go. Pairs are packed
    before they are shuffled, a few bytes each, so that repeats of an edge meet without a row for each."""

    def run(key: tuple, group: pa.Table) -> pa.Table:
        src, dst = _in_order(*_ends(group))
        a, b = (x.as_py() for x in key)
        return pa.table({"a": [a], "b": [b], "n": [len(src)], "src": [_squeeze(src)], "dst": [_squeeze(dst)]}, schema=_PACKED)

    return materialize(packed(ends(pairs), c).groupBy("a", "b").applyInArrow(run, PACKED))


CELL_EDGES = 4_000_000  # of a cell that meets what is known of its vertices


def with_vertices(cells: DataFrame, vertices: DataFrame, m: int, pack, work, kind: str) -> DataFrame:
    """work(src, dst, rows), which gives a table, of every cell: its edges and what `pack` made of the vertices of both
    its colours. pack(batch) gives (v, bytes) pairs of arrays of vertices of one colour for each batch of `vertices`
    (first column v), so that edges are dealt once and vertices once for each colour, all packed."""
    c = max(LEAST_COLOURS, math.ceil(math.sqrt(2 * m / CELL_EDGES)))

    def run(batches):
        for batch in batches:
            at = colour(batch["v"].to_numpy(), c)
            for x in np.unique(at):
                yield pa.RecordBatch.from_pydict({"x": pa.array([x], pa.int32()), "known": pa.array([pack(batch.take(pa.array(np.flatnonzero(at == x))))], pa.binary())})

    ship(cells.sparkSession)
    known = vertices.mapInArrow(run, "x int, known binary").withColumn("y", F.explode(F.sequence(F.lit(0), F.lit(c - 1))))
    nothing = F.lit(None).cast("binary")
    known = known.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), F.lit(0).cast("long").alias("n"), nothing.alias("src"), nothing.alias("dst"), "known")
    both = packed(cells, c).select("*", nothing.alias("known")).unionAll(known)

    def cell(key: tuple, group: pa.Table) -> pa.Table:
        rows = group["known"].drop_null().to_pylist()
        group = group.filter(pa.compute.is_valid(group["src"]))
        return work(*(_ends(group) if group.num_rows else [np.empty(0, np.int64)] * 2), rows)

    return both.repartition(min(c * (c + 1) // 2, 2000), "a", "b").groupBy("a", "b").applyInArrow(cell, kind)


def coded(cells: DataFrame, m: int) -> DataFrame:
    """A packed table, as is the given one, of the codes by_degree gives to ids from 0 to 2^40 - 1."""

    def pack(batch):
        v, deg = batch["v"].to_numpy(), batch["deg"].to_numpy()
        if len(v) and (v.min() < 0 or v.max() >> ID_BITS):
            raise ValueError(f"vertex ids from 0 to 2^{ID_BITS} - 1 are needed (see model.renumbered)")
        order = np.argsort(v)
        return np.concatenate([v[order], deg[order]]).astype(np.int64).tobytes()

    def work(src, dst, rows):
        both = [np.frombuffer(x, np.int64).reshape(2, -1) for x in rows]
        v, deg = np.concatenate(both, 1) if both else np.empty((2, 0), np.int64)
        order = np.argsort(v)
        v, code = v[order], (np.minimum(deg, MOST_DEGREE) << ID_BITS | v)[order]
        x, y = code[np.searchsorted(v, src)], code[np.searchsorted(v, dst)]
        src, dst = _in_order(np.minimum(x, y), np.maximum(x, y))
        return pa.table({"n": [len(src)], "src": [_squeeze(src)], "dst": [_squeeze(dst)]}, schema=pa.schema(list(_PACKED)[2:]))

    return materialize(with_vertices(cells, degrees_of(cells), m, pack, work, "n long, src binary, dst binary"))


def extended(pairs: DataFrame) -> DataFrame:
    """a0, a1, a2 of the triangles of a graph, by degree and id: an edge, and a vertex after it that both its ends see.
    Edges are extended inside blocks, so that no wedge is a row."""
    cells = stored(pairs)
    m = edges_of(cells)
    least, most = degrees_of(cells).agg(F.min("v"), F.max("v")).first()
    if least is not None and (least < 0 or most >> ID_BITS):
        number = numbers(degrees_of(cells))
        end = lambda v, k: number.select(F.col("v").alias(v), F.col("k").alias(k))
        t = extended(unpacked(cells).join(end("src", "a"), "src").join(end("dst", "b"), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst")))
        for x in t.columns:
            t = t.join(end(f"{x}v", x), x).drop(x).withColumnRenamed(f"{x}v", x)
        return t.select("a0", "a1", "a2")
    ordered, c = coded(cells, m), colours_for(m)
    schema = pa.schema([(x, pa.int64()) for x in ("a0", "a1", "a2")])

    def work(block):
        for found in block.triangles():
            t = np.sort(np.stack([block.ids[x] for x in found], 1), 1) & ((1 << ID_BITS) - 1)
            yield pa.table({x: np.ascontiguousarray(t[:, i]) for i, x in enumerate(schema.names)}, schema=schema)

    forget(cells)
    return _in_blocks(packed(ordered, c), 3, c, work, "a0 long, a1 long, a2 long", schema)


def unpacked(cells: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            for n, src, dst in zip(batch["n"].to_pylist(), batch["src"], batch["dst"]):
                yield pa.RecordBatch.from_pydict({"src": _swell(src.as_py(), n), "dst": _swell(dst.as_py(), n)})

    ship(cells.sparkSession)
    return cells.select("n", "src", "dst").mapInArrow(run, "src long, dst long")


def edges_of(cells: DataFrame) -> int:
    return cells.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def degrees_of(cells: DataFrame) -> DataFrame:
    """v, deg of the vertices of a packed table."""

    def run(batches):
        for batch in batches:
            for n, src, dst in zip(batch["n"].to_pylist(), batch["src"], batch["dst"]):
                v, times = np.unique(np.concatenate([_swell(src.as_py(), n), _swell(dst.as_py(), n)]), return_counts=True)
                yield pa.RecordBatch.from_pydict({"v": v, "deg": times.astype(np.int64)})

    ship(cells.sparkSession)
    return cells.select("n", "src", "dst").mapInArrow(run, "v long, deg long").groupBy("v").agg(F.sum("deg").alias("deg"))


def _numbered(ends: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The ids in their order and the places of both ends in it; by a table of all numbers where it is not longer than the ends are."""
    top = max((int(v.max()) for v in ends if len(v)), default=0)
    if top <= 8 * len(ends[0]) and min((int(v.min()) for v in ends if len(v)), default=0) >= 0:
        place = np.zeros(top + 1, np.int32)
        for v in ends:
            place[v] = 1
        ids = np.flatnonzero(place)
        np.cumsum(place, out=place)
        place -= 1
        return ids, place[ends.pop(0)], place[ends.pop(0)]
    ids = np.unique(np.concatenate([np.unique(v) for v in ends]))
    return ids, *[np.searchsorted(ids, ends.pop(0)).astype(np.int32) for _ in range(2)]


class Block:
    """The oriented graph of a block: vertices by degree, out-neighbours in order, colours."""

    def __init__(self, ends: list[np.ndarray], kind: tuple[int, ...], c: int):
        """ends: src and dst, which are taken out of the list, so that they go as soon as they are numbered."""
        ids, x, y = _numbered(ends)
        self.n = n = len(ids)
        order = np.argsort(np.bincount(x, minlength=n) + np.bincount(y, minlength=n), kind="stable")
        place = np.empty(n, np.int32)
        place[order] = np.arange(n, dtype=np.int32)
        x, y = place[x], place[y]
        key = np.minimum(x, y).astype(np.int64) * n + np.maximum(x, y)
        del x, y
        key.sort()
        self.low, self.out = (key // n).astype(np.int32), (key % n).astype(np.int32)
        self.size = np.bincount(self.low, minlength=n)
        self.start = np.concatenate([[0], np.cumsum(self.size)])
        self.ids, self.kind, self.colour = ids[order], kind, colour(ids[order], c)

    def triangles(self):
        """Batches u, v, w of all triangles of the block's own colours."""
        n, most = self.n, max(1, MARKS // max(1, self.n))
        paths = np.concatenate([[0], np.cumsum(self.size[self.out])])[self.start]  # two-step paths from vertices before
        mark = np.zeros(most * n, bool)
        different, want, s = len(set(self.kind)) in (1, len(self.kind)), sum(self.kind), 0
        while s < n:
            e = min(s + most, max(s + 1, int(np.searchsorted(paths, paths[s] + WEDGES, "right")) - 1), n)
            here = slice(self.start[s], self.start[e])
            row, v = (self.low[here] - s).astype(np.int64) * n, self.out[here]
            if paths[e] > paths[s]:
                mark[row + v] = True
                each = self.size[v]
                at = np.arange(int(each.sum())) + np.repeat(self.start[v] - np.cumsum(each) + each, each)
                w = self.out[at]
                hit = np.flatnonzero(mark[np.repeat(row, each) + w])
                if len(hit):
                    first = np.searchsorted(np.cumsum(each), hit, "right")
                    u, v2, w = self.low[here][first], v[first], w[hit]
                    if not different:
                        own = self.colour[u] + self.colour[v2] + self.colour[w] == want
                        u, v2, w = u[own], v2[own], w[own]
                    yield u, v2, w
                mark[row + v] = False
            s = e

    def count3(self) -> int:
        return sum(len(u) for u, _, _ in self.triangles())

    def count4(self) -> int:
        """By the graph among each vertex's out-neighbours, as bits by the colour of the end that is last."""
        total, shades = 0, max(self.kind) + 1
        place, last = np.full(self.n, -1, np.int32), {x: self._last(x, shades) for x in set(self.kind)}
        word = lambda x: np.packbits(np.pad(x, ((0, 0), (0, -x.shape[1] % 64))), axis=1).view(np.uint64)
        for u in np.flatnonzero(self.size > 2):
            near = self.out[self.start[u] : self.start[u + 1]]
            near = near[np.argsort(self.colour[near], kind="stable")]
            d, each, shade = len(near), self.size[near], self.colour[near]
            place[near] = np.arange(d, dtype=np.int32)
            at = np.arange(int(each.sum())) + np.repeat(self.start[near] - np.cumsum(each) + each, each)
            q = place[self.out[at]]
            place[near] = -1
            there = np.flatnonzero(q >= 0)
            r, q = np.repeat(np.arange(d, dtype=np.int32), each)[there], q[there]
            if len(r) < 3:
                continue
            bits = np.zeros((d, d), bool)
            bits[r, q] = True
            missing = last[self.colour[u]][shade[r] * shades + shade[q]]
            for x in set(self.kind):
                own, (lo, hi) = np.flatnonzero(missing == x), np.searchsorted(shade, (x, x + 1))
                if len(own) and hi > lo:
                    row = word(bits[:, lo:hi])
                    step = max(1, (1 << 20) // row.shape[1])
                    for s in range(0, len(own), step):
                        z = own[s : s + step]
                        total += int(np.bitwise_count(row[r[z]] & row[q[z]]).sum(dtype=np.int64))
        return total

    def _last(self, first: int, shades: int) -> np.ndarray:
        """The colour that the block has left after `first` and two more, by those two; -1 where they are not in it."""
        out = np.full(shades * shades, -1, np.int64)
        for x, y in permutations(range(4), 2):
            z = [i for i in range(4) if i not in (x, y)]
            if first in (self.kind[i] for i in z):
                rest = [self.kind[i] for i in z]
                rest.remove(first)
                out[self.kind[x] * shades + self.kind[y]] = rest[0]
        return out


def _in_blocks(parts: DataFrame, k: int, c: int, work, kind: str, schema: pa.Schema, wave: tuple[int, int] = (0, 1)) -> DataFrame:
    """work(Block), which yields tables, of every block of a packed table, sent on as they come; of waves, only of those of number wave[0] of wave[1]."""
    more = F.array(*[F.array(*[F.lit(x) for x in p]) for p in combinations_with_replacement(range(c), k - 2)])
    block = lambda p: F.array_sort(F.concat(F.array("a", "b"), p))
    of = F.transform(more, block)
    if wave[1] > 1:
        of = F.filter(of, lambda x: F.pmod(F.xxhash64(x), F.lit(wave[1])) == wave[0])
    dealt = parts.withColumn("block", F.explode(of))
    blocks = math.comb(c + k - 1, k)
    dealt = dealt.select("block", "n", "src", "dst").repartition(min(blocks, 2000), "block")

    def run(key: tuple[pa.Scalar, ...], group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ends = _ends(pa.Table.from_batches(group))
        for table in work(Block(ends, tuple(key[0].as_py()), c)):
            yield from table.cast(schema).combine_chunks().to_batches(ROWS)

    ship(parts.sparkSession)
    return dealt.groupBy("block").applyInArrow(run, kind)


def _in_waves(cells: DataFrame, k: int, m: int, work, kind: str, schema: pa.Schema) -> DataFrame:
    """The same, written; the shuffle files of a wave go before the next one is dealt."""
    c = colours_for(m, k)
    waves = max(1, -(-m * copies(c, k) // max(m, WAVE_EDGES)))
    parts = materialize(packed(cells, c))
    done = [materialize(_in_blocks(parts, k, c, work, kind, schema, (w, waves))) for w in range(waves)]
    forget(parts)
    return reduce(DataFrame.unionAll, done)


def _counted(k: int):
    def work(block):
        yield pa.table({"found": [block.count3() if k == 3 else block.count4()]}, schema=_FOUND)

    return work


_FOUND = pa.schema([("found", pa.int64())])


def count(edges: DataFrame, k: int = 3, m: int | None = None, c: int | None = None) -> DataFrame:
    """One row: cliques. edges: canonical, best a written table, as it is read twice (m: its number of rows)."""
    c = c or colours_for(edges.count() if m is None else m, k)
    return _in_blocks(packed(edges, c), k, c, _counted(k), "found long", _FOUND).agg(F.coalesce(F.sum("found"), F.lit(0)).alias("cliques"))


def count_stored(cells: DataFrame, k: int = 3, m: int | None = None) -> DataFrame:
    """One row: cliques of a packed table; at most a wave of its copies is on disk."""
    found = _in_waves(cells, k, edges_of(cells) if m is None else m, _counted(k), "found long", _FOUND)
    return found.agg(F.coalesce(F.sum("found"), F.lit(0)).alias("cliques"))


def count4_by_links(cells: DataFrame, m: int | None = None) -> DataFrame:
    """One row: 4-cliques, as triangles in the links of vertices. The link of a vertex has an edge for each of the
    triangles of which it is the first. Triangles are listed in blocks and kept packed, so no pair of them is a row."""
    schema = pa.schema([("n", pa.int64()), ("a", pa.binary()), ("src", pa.binary()), ("dst", pa.binary())])

    def work(block):
        held, n = [], 0
        for found in block.triangles():
            held.append(np.sort(np.stack([block.ids[x] for x in found], 1), 1))
            n += len(held[-1])
            if n >= PACK_EDGES:
                yield from rows(np.concatenate(held))
                held, n = [], 0
        if n:
            yield from rows(np.concatenate(held))

    def rows(t):
        t = t[np.lexsort((t[:, 2], t[:, 1], t[:, 0]))]
        yield pa.table({"n": [len(t)]} | {name: [_squeeze(np.ascontiguousarray(t[:, i]))] for i, name in enumerate(("a", "src", "dst"))}, schema=schema)

    listed = _in_waves(cells, 3, edges_of(cells) if m is None else m, work, "n long, a binary, src binary, dst binary", schema)
    groups = max(1, -(-edges_of(listed) // LINK_TRIANGLES))
    kind = "g int, n long, a binary, src binary, dst binary"

    def deal(batches):
        for batch in batches:
            for n, *columns in zip(*(batch[x].to_pylist() for x in ("n", "a", "src", "dst"))):
                columns = [_swell(x, n) for x in columns]
                g = colour(columns[0], groups)
                order = np.argsort(g, kind="stable")
                g = g[order]
                cuts = np.flatnonzero(np.diff(g, prepend=-1))
                for s, e in zip(cuts, [*cuts[1:], n]):
                    at = order[s:e]
                    yield pa.RecordBatch.from_pydict({"g": pa.array([g[s]], pa.int32()), "n": [int(e - s)]} | {x: [_squeeze(v[at])] for x, v in zip(("a", "src", "dst"), columns)})

    def run(group: pa.Table) -> pa.Table:
        n = group["n"].to_pylist()
        a, x, y = (np.concatenate([_swell(v.as_py(), z) for v, z in zip(group[name], n)]) for name in ("a", "src", "dst"))
        ids = np.unique(np.concatenate([np.unique(v) for v in (a, x, y)]))
        a, x, y = (np.searchsorted(ids, v) for v in (a, x, y))  # a vertex of the link of a is the pair of both
        ends = [a * len(ids) + x, a * len(ids) + y]
        del a, x, y
        return pa.table({"found": [Block(ends, (0, 0, 0), 1).count3()]}, schema=_FOUND)

    found = listed.mapInArrow(deal, kind).repartition(min(groups, 2000), "g").groupBy("g").applyInArrow(run, "found long")
    return found.agg(F.coalesce(F.sum("found"), F.lit(0)).alias("cliques"))


def triangles(edges: DataFrame, m: int | None = None, c: int | None = None) -> DataFrame:
    """a < b < c of every triangle, once."""
    c = c or colours_for(edges.count() if m is None else m)
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("c", pa.int64())])

    def work(block):
        for found in block.triangles():
            t = np.sort(np.stack([block.ids[x] for x in found], 1), 1)
            yield pa.table({name: t[:, i] for i, name in enumerate("abc")}, schema=schema)

    return _in_blocks(packed(edges, c), 3, c, work, "a long, b long, c long", schema)


LEVEL, NEVER = 40, 1 << 20  # bits of a vertex's number under its level; the level of vertices that have none


def by_level(edges: DataFrame, levels: DataFrame, c: int | None = None) -> DataFrame:
    """level, lowest (1, 2 or 3), triangles: by the least level of a triangle's vertices and how many of them have it.
    levels: v, level from 0; triangles of vertices without a level are left out. edges: best a written table."""
    number = numbers(edges.select(F.explode(F.array("src", "dst")).alias("v")))
    level = F.coalesce(F.col("level").cast("long"), F.lit(NEVER))
    code = number.join(levels.select("v", "level"), "v", "left").select("v", (F.shiftleft(level, LEVEL) + F.col("k")).alias("code"))
    end = lambda x, y: code.select(F.col("v").alias(x), F.col("code").alias(y))
    coded = materialize(edges.join(end("src", "a"), "src").join(end("dst", "b"), "dst").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")))
    schema = pa.schema([("level", pa.int64()), ("lowest", pa.int32()), ("triangles", pa.int64())])

    def work(block):
        at = block.ids >> LEVEL
        for found in block.triangles():
            ends = np.stack([at[x] for x in found])
            least = ends.min(0)
            kind, times = np.unique(4 * least + (ends == least).sum(0), return_counts=True)
            yield pa.table({"level": kind // 4, "lowest": (kind % 4).astype(np.int32), "triangles": times}, schema=schema)

    c = c or colours_for(coded.count())
    found = _in_blocks(packed(coded, c), 3, c, work, "level long, lowest int, triangles long", schema)
    return found.where(F.col("level") < NEVER).groupBy("level", "lowest").agg(F.sum("triangles").alias("triangles"))


ID_BITS, MOST_DEGREE = 40, (1 << 23) - 1  # bits of an id under its vertex's degree; from this degree on the id decides


def by_degree(edges: DataFrame) -> DataFrame:
    """The edges between codes that order the vertices by (degree, id): ids from 0 to 2^40 - 1, which stay the codes'
    low bits, or else numbers in the order of the ids. edges: best a written table."""
    least, most = edges.agg(F.min("src"), F.max("dst")).first()
    if least is not None and (least < 0 or most >> ID_BITS):
        edges = materialize(renumbered(edges))
    code = degrees(edges).select("v", (F.shiftleft(F.least("deg", F.lit(MOST_DEGREE)), ID_BITS) + F.col("v")).alias("code"))
    end = lambda x, y: code.select(F.col("v").alias(x), F.col("code").alias(y))
    return materialize(edges.join(end("src", "a"), "src").join(end("dst", "b"), "dst").select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")))


class Pairs:
    """All edges at the vertices of two colours, as lists of neighbours: the common neighbours of a vertex of the first
    and one of the second are all here. Vertices are in the order of their ids, which by_degree makes that of degrees."""

    def __init__(self, ends: list[np.ndarray], kind: tuple[int, int], c: int):
        ids = np.unique(np.concatenate([np.unique(v) for v in ends]))
        x, y = (np.searchsorted(ids, ends.pop(0)) for _ in range(2))
        self.n = n = len(ids)
        key = np.concatenate([x * n + y, y * n + x])
        del x, y
        key.sort()
        self.tail, self.near = (key // n).astype(np.int32), (key % n).astype(np.int32)
        self.size = np.bincount(self.tail, minlength=n)
        self.start = np.concatenate([[0], np.cumsum(self.size)])
        self.colour, self.kind = colour(ids, c), kind

    def cycles(self) -> int:
        """4-cycles by their greatest vertex, of one colour, and the opposite one, of the other."""
        i, j = self.kind
        total = 0
        for x, y in ((i, j), (j, i)) if i != j else ((i, i),):
            last = self.colour[self.near] == y
            w_of, size = self.near[last], np.bincount(self.tail[last], minlength=self.n)
            start = np.concatenate([[0], np.cumsum(size)])
            first = (self.colour[self.tail] == x) & (self.near < self.tail)
            u_of, v_of = self.tail[first], self.near[first]
            before = np.concatenate([[0], np.cumsum(size[v_of])])
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(u_of)) + 1, [len(u_of)]]) if len(u_of) else np.zeros(1, np.int64)
            before, s = before[cuts], 0
            while s < len(cuts) - 1:
                e = max(s + 1, int(np.searchsorted(before, before[s] + WEDGES, "right")) - 1)
                u, v = u_of[cuts[s] : cuts[e]], v_of[cuts[s] : cuts[e]]
                each = size[v]
                w = w_of[np.arange(int(each.sum())) + np.repeat(start[v] - np.cumsum(each) + each, each)]
                u = np.repeat(u, each)
                low = w < u
                key = u[low].astype(np.int64) * self.n + w[low]
                key.sort()
                times = np.diff(np.concatenate([[0], np.flatnonzero(np.diff(key)) + 1, [len(key)]]))
                total += int((times * (times - 1) // 2).sum())
                s = e
        return total

    def common(self):
        """Batches u, w, times: the edges between both colours, each once, and their common neighbours."""
        i, j = self.kind
        a, b = self.colour[self.tail], self.colour[self.near]
        own = np.flatnonzero((self.near < self.tail) & ((a == i) & (b == j) | (a == j) & (b == i)))
        u_of, w_of = self.tail[own], self.near[own]  # the first has the longer list
        before = np.concatenate([[0], np.cumsum(self.size[w_of])])
        most = max(1, MARKS // max(1, self.n))
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(u_of)) + 1, [len(u_of)]]) if len(u_of) else np.zeros(1, np.int64)
        mark = np.zeros(most * self.n, bool)
        before, s = before[cuts], 0
        while s < len(cuts) - 1:
            e = max(s + 1, min(s + most, int(np.searchsorted(before, before[s] + WEDGES, "right")) - 1))
            u, w = u_of[cuts[s] : cuts[e]], w_of[cuts[s] : cuts[e]]
            tops = u_of[cuts[s:e]]
            row = np.repeat(np.arange(e - s), self.size[tops]) * self.n
            row += self.near[np.arange(len(row)) + np.repeat(self.start[tops] - np.cumsum(self.size[tops]) + self.size[tops], self.size[tops])]
            mark[row] = True
            each = self.size[w]
            at = np.arange(int(each.sum())) + np.repeat(self.start[w] - np.cumsum(each) + each, each)
            hit = mark[np.repeat(np.searchsorted(tops, u) * self.n, each) + self.near[at]]
            mark[row] = False
            yield u, w, np.diff(np.concatenate([[0], np.cumsum(hit)])[np.concatenate([[0], np.cumsum(each)])])
            s = e


FOURS = ("triangle", "path4", "paw", "cycle4", "diamond")


def fours(edges: DataFrame, c: int | None = None) -> DataFrame:
    """One row: copies of the triangle and of the connected patterns of four vertices that are neither stars nor complete.

    Vertices get one of c colours and a block is a pair of colours; an edge goes, packed, to the 2 c - 1 blocks at most
    that hold the colour of an end. A 4-cycle is found with its greatest vertex, as pairs of ways to the opposite one;
    the others come from the common neighbours and the degrees of each edge's ends. No wedge is a row.
    """
    coded = by_degree(edges)
    c = c or max(LEAST_COLOURS, math.ceil(4 * coded.count() / BLOCK_EDGES))
    block = lambda x: F.transform(F.sequence(F.lit(0), F.lit(c - 1)), lambda y: F.array(F.least(F.col(x), y), F.greatest(F.col(x), y)))
    dealt = packed(coded, c).withColumn("block", F.explode(F.array_distinct(F.concat(block("a"), block("b")))))
    parts = dealt.select("block", "n", "src", "dst").repartition(min(c * (c + 1) // 2, 2000), "block")
    names = ("closed", "paths", "tails", "cycle4", "diamond")

    def run(key: tuple, group: pa.Table) -> pa.Table:
        n = group["n"].to_pylist()
        found = Pairs([np.concatenate([_swell(x.as_py(), y) for x, y in zip(group[name], n)]) for name in ("src", "dst")], tuple(key[0].as_py()), c)
        del group
        got = dict.fromkeys(names, 0)
        for u, w, times in found.common():
            a, b = found.size[u] - 1, found.size[w] - 1
            got["closed"] += int(times.sum())
            got["paths"] += int((a * b).sum())
            got["tails"] += int((times * (a + b - 2)).sum())
            got["diamond"] += int((times * (times - 1) // 2).sum())
        got["cycle4"] = found.cycles()
        return pa.table({name: pa.array([got[name]], pa.int64()) for name in names})

    total = parts.groupBy("block").applyInArrow(run, ", ".join(f"{x} long" for x in names)).agg(*[F.coalesce(F.sum(x), F.lit(0)).alias(x) for x in names])
    return total.select(F.expr("closed div 3 as triangle"), F.expr("paths - closed as path4"), F.expr("tails div 2 as paw"), "cycle4", "diamond")
