"""Counting copies of any connected pattern of up to five vertices.

Each copy in an acyclic orientation of the graph has one orientation of the pattern, so the classes of
acyclic orientations are counted one by one. Of a class, the largest set of vertices that one root reaches
is listed as an out-tree; arcs among them are looked up (list 1), and the one or two vertices left, which
only have arcs towards the tree or to each other, are counted by lists of out-neighbour sets (list 2) and
of arcs between two such sets (list 3). Vertices of the tree that the lists would count again are taken
off, and the total is divided by the orientation's automorphisms.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from itertools import permutations, product

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import arcs, degrees, numbers
from ..session import ship
from ..storage import materialize
from . import blocks, orient


@dataclass(frozen=True)
class Pattern:
    n: int
    edges: tuple[tuple[int, int], ...]

    def automorphisms(self) -> int:
        have = {frozenset(e) for e in self.edges}
        return sum(all(frozenset((p[a], p[b])) in have for a, b in self.edges) for p in permutations(range(self.n)))


def _p(n: int, text: str) -> Pattern:
    return Pattern(n, tuple((int(e[0]), int(e[1])) for e in text.split()))


# The connected patterns of two to five vertices, by edge list.
NAMED = {
    "edge": _p(2, "01"),
    "wedge": _p(3, "01 02"),
    "triangle": _p(3, "01 02 12"),
    "claw": _p(4, "01 02 03"),
    "path4": _p(4, "01 12 23"),
    "paw": _p(4, "01 02 12 03"),
    "cycle4": _p(4, "01 12 23 30"),
    "diamond": _p(4, "01 02 12 03 13"),
    "k4": _p(4, "01 02 03 12 13 23"),
    "star4": _p(5, "01 02 03 04"),
    "fork": _p(5, "01 02 03 34"),
    "path5": _p(5, "01 12 23 34"),
    "cricket": _p(5, "01 02 12 03 04"),
    "bull": _p(5, "01 02 12 03 14"),
    "triangle_tail2": _p(5, "01 02 12 03 34"),
    "banner": _p(5, "01 12 23 30 04"),
    "cycle5": _p(5, "01 12 23 34 40"),
    "dart": _p(5, "01 02 12 03 13 04"),
    "butterfly": _p(5, "01 02 12 03 04 34"),
    "kite": _p(5, "01 02 12 13 23 34"),
    "house": _p(5, "01 12 23 30 04 14"),
    "k23": _p(5, "02 03 04 12 13 14"),
    "book3": _p(5, "01 02 12 03 13 04 14"),
    "k4_pendant": _p(5, "01 02 03 12 13 23 04"),
    "gem": _p(5, "01 02 03 04 12 23 34"),
    "wheel4_minus_spoke": _p(5, "12 23 34 41 01 02 03"),
    "k5_minus_path": _p(5, "01 02 03 04 12 13 23 24"),
    "wheel4": _p(5, "01 02 03 04 12 23 34 41"),
    "k5_minus_edge": _p(5, "01 02 03 04 12 13 14 23 24"),
    "k5": _p(5, "01 02 03 04 12 13 14 23 24 34"),
}


@dataclass(frozen=True)
class Oriented:
    """One class: arcs, automorphisms that keep them, the tree in breadth-first order with parents, the rest."""

    arcs: tuple[tuple[int, int], ...]
    aut: int
    order: tuple[int, ...]
    parent: dict
    rest: tuple[int, ...]

    def __hash__(self):
        return hash(self.arcs)


def orientations(p: Pattern) -> list[Oriented]:
    """Acyclic orientations up to isomorphism."""
    seen, out = set(), []
    for bits in product((0, 1), repeat=len(p.edges)):
        a = tuple(sorted((x, y) if b == 0 else (y, x) for b, (x, y) in zip(bits, p.edges)))
        if _cyclic(p.n, a):
            continue
        form = min(tuple(sorted((q[x], q[y]) for x, y in a)) for q in permutations(range(p.n)))
        if form in seen:
            continue
        seen.add(form)
        aut = sum(tuple(sorted((q[x], q[y]) for x, y in a)) == a for q in permutations(range(p.n)))
        order, parent = max((_reach(a, r) for r in range(p.n)), key=lambda t: len(t[0]))
        out.append(Oriented(a, aut, order, parent, tuple(v for v in range(p.n) if v not in order)))
    return out


def _cyclic(n, a) -> bool:
    left = set(range(n))
    while left:
        free = {v for v in left if not any(y == v and x in left for x, y in a)}
        if not free:
            return True
        left -= free
    return False


def _reach(a, root):
    order, parent = [root], {}
    for v in order:
        for x, y in a:
            if x == v and y not in order:
                order.append(y)
                parent[y] = v
    return tuple(order), parent


def tree_copies(g: DataFrame, order: tuple[int, ...], parent: dict, checks: tuple[tuple[int, int], ...] = ()) -> DataFrame:
    """Columns a<vertex>: copies of an out-tree in breadth-first order, one join a vertex; an arc in `checks`
    is looked up as soon as both its ends stand, and no vertex is used twice."""
    first = order[1] if len(order) > 1 else None
    out = g.select(F.col("src").alias(f"a{order[0]}"), F.col("dst").alias(f"a{first}")) if first is not None else arcs(g).select(F.col("src").alias(f"a{order[0]}")).distinct()
    placed = list(order[:2])
    for v in order[2:]:
        step = g.select(F.col("src").alias(f"a{parent[v]}"), F.col("dst").alias(f"a{v}"))
        out = out.join(step, f"a{parent[v]}")
        out = out.where(reduce(lambda x, y: x & y, [F.col(f"a{v}") != F.col(f"a{u}") for u in placed]))
        placed.append(v)
        for x, y in checks:
            if v in (x, y) and x in placed and y in placed:
                out = out.join(hm1(g, f"a{x}", f"a{y}"), [f"a{x}", f"a{y}"], "left_semi")
    return out


def hm1(g: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """List 1: the arcs."""
    return g.select(F.col("src").alias(u), F.col("dst").alias(v))


def out_sets(g: DataFrame, s: int, by: str = "u") -> DataFrame:
    """(vertex, key): every set of s out-neighbours, sorted."""
    out = g.select(F.col("src").alias(by), F.array("dst").alias("key"), F.col("dst").alias("last"))
    for _ in range(s - 1):
        nxt = g.select(F.col("src").alias(by), F.col("dst").alias("x"))
        out = out.join(nxt, by).where("x > last").select(by, F.array_append("key", F.col("x")).alias("key"), F.col("x").alias("last"))
    return out.select(by, "key")


def hm2(g: DataFrame, s: int) -> DataFrame:
    """List 2: for each set of s vertices, how many vertices have arcs to all of it."""
    return out_sets(g, s).groupBy("key").agg(F.count("*").alias("cnt"))


def hm3(g: DataFrame, s1: int, s2: int) -> DataFrame:
    """List 3: for sets of s1 and s2 vertices, how many arcs (u, v) have u before all of the first, v of the second."""
    e = g.select(F.col("src").alias("u"), F.col("dst").alias("v"))
    e = e.join(out_sets(g, s1, "u").withColumnRenamed("key", "key1"), "u") if s1 else e.withColumn("key1", F.array().cast("array<long>"))
    e = e.join(out_sets(g, s2, "v").withColumnRenamed("key", "key2"), "v") if s2 else e.withColumn("key2", F.array().cast("array<long>"))
    return e.groupBy("key1", "key2").agg(F.count("*").alias("cnt"))


class Lists:
    """Lists 2 and 3 of one oriented graph, written once per shape and shared by all classes."""

    def __init__(self, g: DataFrame):
        self.g, self.known = g, {}

    def two(self, s: int) -> DataFrame:
        if s not in self.known:
            self.known[s] = materialize(hm2(self.g, s))
        return self.known[s]

    def three(self, s1: int, s2: int) -> DataFrame:
        if (s1, s2) not in self.known:
            self.known[s1, s2] = materialize(hm3(self.g, s1, s2))
        return self.known[s1, s2]


def _key(vertices) -> Column:
    return F.array_sort(F.array(*[F.col(f"a{v}") for v in vertices])) if vertices else F.array().cast("array<long>")


def _arc(copies: DataFrame, g: DataFrame, x: str, y: str, name: str) -> DataFrame:
    """Adds 0/1: is there an arc from column x to column y."""
    return copies.join(g.select(F.col("src").alias(x), F.col("dst").alias(y), F.lit(1).alias(name)), [x, y], "left").withColumn(name, F.coalesce(name, F.lit(0)))


def completions(copies: DataFrame, g: DataFrame, o: Oriented, lists: Lists) -> DataFrame:
    """Adds `ways`: in how many ways the vertices outside the tree can be chosen."""
    if not o.rest:
        return copies.withColumn("ways", F.lit(1).cast("long"))
    targets = {v: tuple(sorted(y for x, y in o.arcs if x == v and y in o.order)) for v in o.rest}
    inner = [(x, y) for x, y in o.arcs if x in o.rest and y in o.rest]
    out, needed = copies, set()
    sets = {targets[v] for v in o.rest} | ({tuple(sorted({*targets[o.rest[0]], *targets[o.rest[1]]}))} if len(o.rest) == 2 and not inner else set())
    for s in sets:
        needed |= {(t, x) for t in o.order for x in s if t != x}
    if inner:
        needed |= {(t, u) for t in o.order for u in o.order if t != u}
    for t, u in sorted(needed):
        out = _arc(out, g, f"a{t}", f"a{u}", f"e{t}_{u}")
    has = lambda t, s: reduce(lambda x, y: x * y, [F.col(f"e{t}_{u}") for u in s], F.lit(1)) if t not in s else F.lit(0)

    def two(df, key, name):
        s = len(key)
        return df.withColumn("key", _key(key)).join(lists.two(s).withColumnRenamed("cnt", name), "key", "left").drop("key").withColumn(name, F.coalesce(name, F.lit(0)))

    def free(df, s, name):
        """Vertices outside the tree with arcs to all of s."""
        df = two(df, s, name)
        return df.withColumn(name, F.col(name) - reduce(lambda x, y: x + y, [has(t, s) for t in o.order]))

    if len(o.rest) == 1:
        return free(out, targets[o.rest[0]], "ways")
    x, y = o.rest
    if not inner:
        both = tuple(sorted({*targets[x], *targets[y]}))
        out = free(free(free(out, targets[x], "c1"), targets[y], "c2"), both, "c12")
        return out.withColumn("ways", F.col("c1") * F.col("c2") - F.col("c12"))
    x, y = inner[0]
    s1, s2 = targets[x], targets[y]
    three = lists.three(len(s1), len(s2)).withColumnRenamed("cnt", "all")
    out = out.withColumn("key1", _key(s1)).withColumn("key2", _key(s2)).join(three, ["key1", "key2"], "left").drop("key1", "key2")
    ways = F.coalesce("all", F.lit(0))
    for t in o.order:
        # arcs from the tree vertex t into the outside's second set (any head)
        heads = _heads(lists, len(s2)).select(F.col("u").alias(f"a{t}"), F.col("key").alias("key2"), F.col("cnt").alias(f"h{t}"))
        out = out.withColumn("key2", _key(s2)).join(heads, [f"a{t}", "key2"], "left").drop("key2")
        ways = ways - has(t, s1) * F.coalesce(F.col(f"h{t}"), F.lit(0))
        # arcs from anywhere before s1 into the tree vertex t
        tails = tuple(sorted({*s1, t})) if t not in s1 else s1
        out = two(out, tails, f"t{t}")
        ways = ways - (has(t, s2) if s2 else F.lit(1)) * F.col(f"t{t}")
    for t in o.order:
        for u in o.order:
            if t != u:
                ways = ways + F.col(f"e{t}_{u}") * has(t, s1) * has(u, s2)
    return out.withColumn("ways", ways)


def _heads(lists: Lists, s: int) -> DataFrame:
    """(u, key, cnt): out-neighbours of u that have arcs to all of the key."""
    name = ("heads", s)
    if name not in lists.known:
        e = lists.g.select(F.col("src").alias("u"), F.col("dst").alias("v"))
        e = e.join(out_sets(lists.g, s, "v"), "v") if s else e.withColumn("key", F.array().cast("array<long>"))
        lists.known[name] = materialize(e.groupBy("u", "key").agg(F.count("*").alias("cnt")))
    return lists.known[name]


def count(edges: DataFrame, name: str | Pattern, oriented: DataFrame | None = None) -> DataFrame:
    """One row: copies. Complete patterns of three or four vertices, and all of four that are no stars, are counted in
    blocks of colours, without wedge rows."""
    p = NAMED[name] if isinstance(name, str) else name
    if p.n in (3, 4) and len(p.edges) == p.n * (p.n - 1) // 2:
        return blocks.count(edges, p.n).withColumnRenamed("cliques", "copies")
    if p.n > 2 and len(p.edges) == p.n - 1 and all(0 in e for e in p.edges):
        return star(edges, p.n - 1)
    if four := next((x for x in blocks.FOURS if NAMED[x] == p), None):
        return blocks.fours(edges).select(F.col(four).alias("copies"))
    g = oriented if oriented is not None else materialize(orient.low_outdegree(edges))
    lists, parts = Lists(g), []
    for o in orientations(p):
        checks = tuple((x, y) for x, y in o.arcs if x in o.order and y in o.order and o.parent.get(y) != x)
        done = completions(tree_copies(g, o.order, o.parent, checks), g, o, lists)
        parts.append(done.agg(F.coalesce(F.sum("ways"), F.lit(0)).alias("w")).select(F.expr(f"w div {o.aut}").alias("w")))
    return reduce(DataFrame.unionAll, parts).agg(F.sum("w").alias("copies"))


def embeddings(edges: DataFrame, p: Pattern, keys: tuple[str, ...] = ()) -> DataFrame:
    """Labelled copies by joins on both directions of the edges: columns keys, a0, a1, ..."""
    both = edges.select(*keys, "src", "dst").unionAll(edges.select(*keys, F.col("dst").alias("src"), F.col("src").alias("dst")))
    placed, todo, out = [0], list(p.edges), None
    while todo:
        x, y = next((x, y) for x, y in todo if x in placed or y in placed)
        todo.remove((x, y))
        if x not in placed:
            x, y = y, x
        step = both.select(*keys, F.col("src").alias(f"a{x}"), F.col("dst").alias(f"a{y}"))
        if out is None:
            out, placed = step, [x, y]
        elif y in placed:
            out = out.join(step, [*keys, f"a{x}", f"a{y}"], "left_semi")
        else:
            out = out.join(step, [*keys, f"a{x}"]).where(reduce(lambda a, b: a & b, [F.col(f"a{y}") != F.col(f"a{u}") for u in placed]))
            placed.append(y)
    return out


def brute(edges: DataFrame, name: str) -> DataFrame:
    p = NAMED[name]
    return embeddings(edges, p).agg(F.count("*").alias("n")).select(F.expr(f"n div {p.automorphisms()}").alias("copies"))


def star(edges: DataFrame, leaves: int) -> DataFrame:
    """Stars by binomials of the degrees; one leaf is an edge."""
    d = F.col("deg").cast("decimal(38,0)")
    total = F.lit(1).cast("decimal(38,0)")
    for i in range(leaves):
        total = (total * (d - i)).cast("decimal(38,0)")
        total = F.floor(total / (i + 1)).cast("decimal(38,0)")  # exact: a product of i + 1 successors
    s = degrees(edges).where(F.col("deg") >= leaves).agg(F.coalesce(F.sum(total), F.lit(0)).cast("decimal(38,0)").alias("s"))
    return s.select((F.floor(F.col("s") / 2) if leaves == 1 else F.col("s")).cast("long").alias("copies"))


def extend(copies: DataFrame, g: DataFrame, frm: int, to: int, checks: tuple[tuple[int, int], ...] = ()) -> DataFrame:
    """One more vertex of a partial copy along an arc, with arcs to look up."""
    placed = [int(c[1:]) for c in copies.columns if c[0] == "a" and c[1:].isdigit()]
    out = copies.join(g.select(F.col("src").alias(f"a{frm}"), F.col("dst").alias(f"a{to}")), f"a{frm}")
    out = out.where(reduce(lambda a, b: a & b, [F.col(f"a{to}") != F.col(f"a{u}") for u in placed]))
    for x, y in checks:
        out = out.join(hm1(g, f"a{x}", f"a{y}"), [f"a{x}", f"a{y}"], "left_semi")
    return out


FOUR = ("claw", "path4", "paw", "cycle4", "diamond", "k4")


def induced_matrix(names: tuple[str, ...] = FOUR) -> list[list[int]]:
    """Entry (a, b): how many copies of pattern a lie in pattern b's vertex set when only b's edges are there."""
    out = []
    for a in names:
        p = NAMED[a]
        row = []
        for b in names:
            have = {frozenset(e) for e in NAMED[b].edges}
            n = sum(all(frozenset((q[x], q[y])) in have for x, y in p.edges) for q in permutations(range(p.n)))
            row.append(n // p.automorphisms())
        out.append(row)
    return out


def induced4(edges: DataFrame) -> DataFrame:
    """pattern, copies, induced of the connected four-vertex patterns, by inverting the triangular system."""
    got = {n: count(edges, n).first()[0] for n in FOUR}
    m, solved = induced_matrix(), {}
    for i in reversed(range(len(FOUR))):
        name = FOUR[i]
        solved[name] = (got[name] - sum(m[i][j] * solved[FOUR[j]] for j in range(len(FOUR)) if j != i and FOUR[j] in solved and m[i][j])) // m[i][i]
    return edges.sparkSession.createDataFrame([(n, int(got[n]), int(solved[n])) for n in FOUR], "pattern string, copies long, induced long")


def disconnected(edges: DataFrame) -> DataFrame:
    """Copies of two disjoint edges and of an edge beside a triangle, from connected counts."""
    m = edges.agg(F.count("*").alias("m"))
    w = count(edges, "wedge").withColumnRenamed("copies", "w")
    t, paw = count(edges, "triangle").withColumnRenamed("copies", "t"), count(edges, "paw").withColumnRenamed("copies", "paw")
    x = m.join(F.broadcast(w)).join(F.broadcast(t)).join(F.broadcast(paw))
    return x.select(F.expr("m * (m - 1) div 2 - w").alias("two_edges"), F.expr("t * (m - 3) - paw").alias("edge_and_triangle"))


def _form(edges) -> tuple:
    """The edges under the numbering of their vertices that comes first; the same for isomorphic graphs only."""
    at = {v: i for i, v in enumerate(sorted({v for e in edges for v in e}))}
    numbered = [(at[x], at[y]) for x, y in edges]
    return min(tuple(sorted((min(q[x], q[y]), max(q[x], q[y])) for x, y in numbered)) for q in permutations(range(len(at))))


def catalogue(vertices: DataFrame) -> DataFrame:
    """pattern, vertices, edges, automorphisms, classes, and classes by out-tree size, of the patterns that the pairs of
    the first five vertices (one column) hold: every set of pairs that is connected, once up to isomorphism."""
    known = vertices.select(F.col(vertices.columns[0]).alias("v"))
    number = numbers(known.where("v is not null")).where("k < 5")
    pairs = number.select(F.col("k").alias("x")).join(number.select(F.col("k").alias("y"))).where("x < y")
    every = pairs.agg(F.sort_array(F.collect_list(F.struct("x", "y"))).alias("pairs"))
    chosen = every.where("size(pairs) > 0").select("pairs", F.explode(F.expr("sequence(1L, shiftleft(1L, size(pairs)) - 1)")).alias("mask")).repartition(8, "mask")
    sets = chosen.select(F.expr("filter(pairs, (p, i) -> shiftright(mask, i) & 1 = 1)").alias("edges"))

    def name(batches):
        names = {_form(p.edges): n for n, p in NAMED.items()}
        for batch in batches:
            forms = {_form([(e["x"], e["y"]) for e in row]) for row in batch["edges"].to_pylist()}
            yield pa.RecordBatch.from_pydict({"pattern": [names[x] for x in forms if x in names]}, schema=pa.schema([("pattern", pa.string())]))

    def describe(batches):
        for batch in batches:
            for n in batch["pattern"].to_pylist():
                p, o = NAMED[n], orientations(NAMED[n])
                by = " ".join(f"{s}:{sum(len(x.order) == s for x in o)}" for s in sorted({len(x.order) for x in o}, reverse=True))
                yield pa.RecordBatch.from_pylist([dict(zip(kind.names, (n, p.n, len(p.edges), p.automorphisms(), len(o), by)))], schema=kind)

    kind = pa.schema([("pattern", pa.string()), *((c, pa.int32()) for c in ("vertices", "edges", "automorphisms", "classes")), ("trees", pa.string())])
    ship(vertices.sparkSession)
    found = sets.mapInArrow(name, "pattern string").distinct()
    return found.mapInArrow(describe, "pattern string, vertices int, edges int, automorphisms int, classes int, trees string")
