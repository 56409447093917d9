"""Estimators from overlapping random induced subgraphs."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import arcs, degrees
from ..session import ship
from ..storage import materialize
from . import blocks, exact, hashing


@dataclass(frozen=True)
class Plan:
    n: int
    m: int
    space: int  # edges a machine may hold
    p: float
    machines: int
    k: int
    eps: float
    mode: str
    seed: int = 1
    verdict: str = ""
    ids: int = 0  # vertex ids are under it; n if not given

    @property
    def largest(self) -> int:
        return self.ids or self.n

    @property
    def prime(self) -> int:
        return hashing.field(self.largest * self.machines)

    @property
    def threshold(self) -> int:
        return hashing.threshold(self.p, self.prime)


def plan(
    n: int,
    m: int,
    space: int | None = None,
    eps: float = 0.5,
    k: int | None = None,
    mode: str = "experiment",
    delta: float = 0.5,
    p: float | None = None,
    machines: int | None = None,
    space_constant: float = 15,
    denominator: str = "edges",
    seed: int = 1,
    triangles: int | None = None,
    vertices: int = 3,
    replicas: str | None = None,
    ids: int = 0,
) -> Plan:
    """Space, sampling probability, machines and independence, with a verdict on the guarantee's conditions.

    theory: p = eps/10 sqrt(S/(m k)), k = 6 ln n; experiment: S = 2 m^delta ln n, total 2 m ln m, p = 1/5
    sqrt(S/(m k)), k = max(2, floor(6.5 ln n)); linear: S = 100 n ln n; explicit: p and machines given.

    The number of machines follows a policy: lemma, 20 / (eps^2 p^(vertices - 1)) for patterns of so many vertices,
    or budget, as many as share a total of 2 m ln m (the default of experiment).
    """
    if m <= 0 or n <= 0:
        raise ValueError("a plan needs edges")
    replicas = replicas or ("budget" if mode == "experiment" else "lemma")
    if replicas not in ("lemma", "budget"):
        raise ValueError(f"replicas is lemma or budget, not {replicas}")
    ln = math.log(max(2, n))
    if mode == "explicit":
        if p is None:
            raise ValueError("an explicit plan names p")
        machines = machines or _machines(replicas, m, space or m, p, eps, vertices)
        return Plan(n, m, space or m, p, machines, k or 6, eps, mode, seed, "explicit", ids)
    k = k or (max(2, int(6.5 * ln)) if mode == "experiment" else max(2, math.ceil(6 * ln)))
    if space is None:
        space = int(2 * m**delta * ln) if mode == "experiment" else int(100 * n * ln) if mode == "linear" else int(space_constant * math.sqrt(m * k) / eps)
    if machines is None and replicas == "budget":
        machines = _machines(replicas, m, space, 1.0, eps, vertices)
    base = m if denominator == "edges" or machines is None else machines
    scale = 0.2 if mode == "experiment" else eps / 10
    p = min(1.0, p if p is not None else scale * math.sqrt(space / (base * k)))
    machines = machines or _machines(replicas, m, space, p, eps, vertices)
    found = []
    if space >= m:
        found.append("the graph fits one machine")
    if space < space_constant * math.sqrt(m * k) / eps:
        found.append("space under the bound for heavy vertices")
    if space < 100 * k * n * n / m:
        found.append("space under the bound for light edges")
    if machines < _machines("lemma", m, space, p, eps, vertices):
        found.append("fewer machines than the lemma asks for")
    if triangles is not None and triangles < 1 / p:
        found.append("fewer triangles than 1/p")
    return Plan(n, m, space, p, machines, k, eps, mode, seed, "; ".join(found) or "guaranteed", ids)


def _machines(replicas: str, m: int, space: int, p: float, eps: float, vertices: int) -> int:
    if replicas == "budget":
        return max(1, -(-int(2 * m * math.log(max(2, m))) // space))
    return max(1, math.ceil(20 / (eps**2 * p ** (vertices - 1))))


def plan_row(spark: SparkSession, p: Plan) -> DataFrame:
    d = asdict(p)
    return spark.createDataFrame([tuple(d.values())], "n long, m long, space long, p double, machines long, k int, eps double, mode string, seed int, verdict string, ids long")


def memberships(edges: DataFrame, p: Plan, reps: int = 1, how: str = "kwise") -> DataFrame:
    """(rep, i, v): the machines of each vertex, worked out where the vertex is; only members become rows.

    kwise: the polynomial at the key of (v, i), for blocks of machines at a time. mixed: a generator seeded by
    the vertex skips from machine to machine, so a vertex costs its memberships and not all machines.
    """
    v = arcs(edges).select(F.col("src").alias("v")).distinct()
    if how == "kwise":
        v = v.select(hashing.checked(F.col("v"), p.largest).alias("v"))
    found = _machines_of(p, reps, how)

    def run(batches):
        for batch in batches:
            for rep, i, v in found(batch.column(0).to_numpy()):
                yield _members(rep, i, v)

    ship(edges.sparkSession)
    return v.mapInArrow(run, "rep int, i long, v long")


def _machines_of(p: Plan, reps: int, how: str):
    """A function of vertices, which gives repetitions with arrays of machines and the vertices that are theirs."""
    tables = [hashing.coefficients(p.k, p.seed, rep, p.prime) for rep in range(reps)] if how == "kwise" else []
    prime, below, machines, seed, share = p.prime, p.threshold, p.machines, p.seed, p.p

    def found(ids: np.ndarray):
        for rep in range(reps):
            if how == "mixed":
                each = [hashing.skips(int(x), share, machines, seed, rep) for x in ids]
                yield rep, np.concatenate([*each, np.empty(0, np.int64)]), np.repeat(ids, [len(f) for f in each])
                continue
            for s in range(0, len(ids), 256):
                part = ids[s : s + 256]
                for start in range(0, machines, 256):
                    i = np.arange(start, min(machines, start + 256))
                    at = np.nonzero(hashing.kwise_values(part[:, None] * machines + i, tables[rep], prime) < below)
                    yield rep, i[at[1]], part[at[0]]

    return found


SLICE = 512  # samples that a cell looks at together, a bit each


def sent_packed(cells: DataFrame, p: Plan, reps: int = 1, hash_: str = "kwise", m: int | None = None) -> DataFrame:
    """rep, i, n, src, dst: the edges each machine gets, packed, some in a row, of a packed table. An edge meets the
    samples of its ends, as bits, in the cell of their colours; neither a membership nor a sent edge is a row."""
    found, machines, samples, largest = _machines_of(p, reps, hash_), p.machines, reps * p.machines, p.largest
    schema = pa.schema([("rep", pa.int32()), ("i", pa.int64()), ("n", pa.int64()), ("src", pa.binary()), ("dst", pa.binary())])

    def pack(batch):
        v = np.sort(batch["v"].to_numpy())
        if hash_ == "kwise" and len(v) and (v[0] < 0 or v[-1] >= largest):
            raise ValueError(f"a vertex id from 0 to {largest - 1} is needed (see model.renumbered)")
        parts = [(np.searchsorted(v, x), rep * machines + i) for rep, i, x in found(v)]
        at, sample = (np.concatenate([x[j] for x in parts] or [np.empty(0, np.int64)]) for j in range(2))
        head = np.array([len(v), len(at)], np.int64).tobytes()
        return pa.compress(head + v.tobytes() + at.astype(np.int32).tobytes() + sample.astype(np.int32).tobytes(), codec="lz4_raw", asbytes=True) + np.int64(16 + 8 * (len(v) + len(at))).tobytes()

    def unpack(row):
        data = pa.decompress(row[:-8], int(np.frombuffer(row[-8:], np.int64)[0]), codec="lz4_raw", asbytes=True)
        n, k = np.frombuffer(data, np.int64, 2)
        return np.frombuffer(data, np.int64, n, 16), np.frombuffer(data, np.int32, k, 16 + 8 * n), np.frombuffer(data, np.int32, k, 16 + 8 * n + 4 * k)

    def work(src, dst, rows):
        known = [unpack(x) for x in rows]
        shift = np.cumsum([0, *(len(v) for v, _, _ in known)])
        v = np.concatenate([v for v, _, _ in known] or [np.empty(0, np.int64)])
        at = np.concatenate([a + s for (_, a, _), s in zip(known, shift)] or [np.empty(0, np.int64)])
        sample = np.concatenate([x for _, _, x in known] or [np.empty(0, np.int32)])
        del known
        order = np.argsort(v)
        x, y = (order[np.searchsorted(v, ends, sorter=order)] for ends in (src, dst))
        out = []
        for first in range(0, samples, SLICE):
            here = np.flatnonzero((sample >= first) & (sample < first + SLICE))
            bit = sample[here] - first
            mask = np.zeros((len(v), -(-min(SLICE, samples - first) // 64)), np.uint64)
            np.bitwise_or.at(mask, (at[here], bit >> 6), np.uint64(1) << (bit & 63).astype(np.uint64))
            for s in range(0, len(src), 1 << 18):
                both = mask[x[s : s + (1 << 18)]] & mask[y[s : s + (1 << 18)]]
                e, word = np.nonzero(both)
                left = both[e, word]
                while len(left):  # the lowest bit of each word
                    low = left & (~left + np.uint64(1))
                    out.append((first + 64 * word + np.bitwise_count(low - np.uint64(1)), s + e))
                    left = left ^ low
                    more = np.flatnonzero(left)
                    e, word, left = e[more], word[more], left[more]
        if not out:
            return schema.empty_table()
        sample, e = (np.concatenate(z) for z in zip(*out))
        del out
        order = np.lexsort((e, sample))  # a cell's edges are in no order across its rows
        sample, e = sample[order], e[order]
        cuts = np.flatnonzero(np.diff(sample, prepend=-1))
        made = []
        for s, t in zip(cuts, [*cuts[1:], len(e)]):
            a, b = blocks._in_order(src[e[s:t]], dst[e[s:t]])
            rep, i = divmod(int(sample[s]), machines)
            made.append((rep, i, len(a), blocks._squeeze(a), blocks._squeeze(b)))
        return pa.table([pa.array(z, f.type) for z, f in zip(zip(*made), schema)], schema=schema)

    m = blocks.edges_of(cells) if m is None else m
    vertices = blocks.degrees_of(cells).select("v")
    return blocks.with_vertices(cells, vertices, m, pack, work, "rep int, i long, n long, src binary, dst binary")


def counted_samples(sent: DataFrame, p: Plan) -> DataFrame:
    """rep, i, edges, hits: a machine counts the triangles of its own sample, which its space bounds."""
    space = p.space
    schema = pa.schema([("rep", pa.int32()), ("i", pa.int64()), ("edges", pa.int64()), ("hits", pa.int64())])

    def run(key: tuple, group: pa.Table) -> pa.Table:
        n = sum(group["n"].to_pylist())
        hits = blocks.Block(blocks._ends(group), (0, 0, 0), 1).count3() if n <= space else 0
        return pa.table({"rep": [key[0].as_py()], "i": [key[1].as_py()], "edges": [n], "hits": [hits]}, schema=schema)

    return sent.groupBy("rep", "i").applyInArrow(run, "rep int, i long, edges long, hits long")


def _members(rep: int, i: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(v), rep, np.int32)), pa.array(i.astype(np.int64)), pa.array(v.astype(np.int64))], ["rep", "i", "v"])


def assign(edges: DataFrame, p: Plan, reps: int = 1, how: str = "lists", hash_: str = "kwise") -> DataFrame:
    """(rep, i, src, dst): the edges each machine gets. lists: memberships joined to both ends; inline: each
    edge tests all machines by itself, nothing is shuffled (k-wise hashes); pairs: all pairs of a sample are looked up."""
    if how == "inline":
        if hash_ != "kwise":
            raise ValueError("inline samples use k-wise hashes")
        parts = []
        for rep in range(reps):
            c = hashing.coefficients(p.k, p.seed, rep, p.prime)
            keep = lambda v: hashing.kwise(hashing.pair_key(F.col(v), F.col("i"), p.largest, p.machines), c, p.prime) < p.threshold  # noqa: E731, B023
            at = edges.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(p.machines - 1)).cast("array<long>")))
            parts.append(at.where(keep("src")).where(keep("dst")).select(F.lit(rep).alias("rep"), "i", "src", "dst"))
        return reduce(DataFrame.unionAll, parts)
    mem = memberships(edges, p, reps, hash_)
    if how == "pairs":
        x = mem.withColumnRenamed("v", "src").join(mem.withColumnRenamed("v", "dst"), ["rep", "i"]).where("src < dst")
        return x.join(edges, ["src", "dst"], "left_semi").select("rep", "i", "src", "dst")
    if how != "lists":
        raise ValueError(f"how is lists, inline or pairs, not {how}")
    mem = materialize(mem)
    e = edges.join(mem.withColumnRenamed("v", "src"), "src")
    return e.join(mem.withColumnRenamed("v", "dst"), ["rep", "i", "dst"], "left_semi").select("rep", "i", "src", "dst")


def _samples(spark: SparkSession, p: Plan, reps: int) -> DataFrame:
    return spark.range(p.machines * reps).select((F.col("id") / p.machines).cast("int").alias("rep"), (F.col("id") % p.machines).alias("i"))


def sizes(sent: DataFrame, p: Plan, reps: int = 1) -> DataFrame:
    """(rep, i, edges, kept) for all machines, empty ones too."""
    every = _samples(sent.sparkSession, p, reps)
    n = sent.groupBy("rep", "i").agg(F.count("*").alias("edges"))
    return every.join(n, ["rep", "i"], "left").select("rep", "i", F.coalesce("edges", F.lit(0)).alias("edges")).withColumn("kept", F.col("edges") <= p.space)


def triangles_within(sent: DataFrame) -> DataFrame:
    """(rep, i): one row per triangle inside a sample."""
    k = ("rep", "i")
    o = sent.select(*k, F.col("src").alias("u"), F.col("dst").alias("v"))
    return exact.close_wedges(o, sent, k).select(*k)


def scaled(sent: DataFrame, hits: DataFrame, p: Plan, reps: int, vertices: int) -> DataFrame:
    """rep, sampled, kept, overflowed, hits, estimate = hits / (p^vertices R), R the samples kept."""
    found = hits.groupBy("rep", "i").agg(F.count("*").alias("hits"))
    return _scaled(sizes(sent, p, reps).join(found, ["rep", "i"], "left"), p, vertices)


def _scaled(samples: DataFrame, p: Plan, vertices: int) -> DataFrame:
    per = samples.groupBy("rep").agg(
        F.count("*").alias("sampled"),
        F.count_if("kept").alias("kept"),
        F.count_if(~F.col("kept")).alias("overflowed"),
        F.coalesce(F.sum(F.when(F.col("kept"), F.col("hits"))), F.lit(0)).alias("hits"),
    )
    return per.withColumn("estimate", F.when(F.col("kept") > 0, F.col("hits") / (F.pow(F.lit(p.p), F.lit(float(vertices))) * F.col("kept"))))


def estimates(edges: DataFrame, p: Plan, reps: int = 1, how: str = "lists", hash_: str = "kwise") -> DataFrame:
    """By samples that are sent packed and counted where they are; by rows if one may be larger than a block, or if
    they are not made by lists. edges: rows, or a packed table."""
    packed = "n" in edges.columns
    if how == "lists" and p.p**2 * p.m <= blocks.BLOCK_EDGES:
        cells = edges if packed else blocks.stored(edges)
        sent = materialize(sent_packed(cells, p, reps, hash_))
        found = materialize(counted_samples(sent, p))
        blocks.forget(sent)
        every = _samples(edges.sparkSession, p, reps).join(F.broadcast(found), ["rep", "i"], "left")
        return _scaled(every.withColumn("kept", F.coalesce("edges", F.lit(0)) <= p.space), p, 3)
    if packed:
        edges = materialize(blocks.unpacked(edges))
    sent = materialize(assign(edges, p, reps, how, hash_))
    fit = sent.join(F.broadcast(sizes(sent, p, reps).where("kept").select("rep", "i")), ["rep", "i"], "left_semi")
    return scaled(sent, triangles_within(fit), p, reps, 3)


estimate_once = estimates


def lower_median(df: DataFrame, col: str, alias: str = "estimate") -> DataFrame:
    a = F.array_sort(F.collect_list(col))
    return df.agg(a.alias("a")).select(F.expr("CASE WHEN size(a) > 0 THEN a[(size(a) - 1) div 2] END").alias(alias))


def estimate_median(edges: DataFrame, p: Plan, reps: int, **options) -> DataFrame:
    return lower_median(estimates(edges, p, reps, **options), "estimate")


def estimate_mom(edges: DataFrame, p: Plan, groups: int, per_group: int, **options) -> DataFrame:
    """Median of the groups' means."""
    e = estimates(edges, p, groups * per_group, **options)
    means = e.groupBy((F.col("rep") % groups).alias("g")).agg(F.avg("estimate").alias("mean"))
    return lower_median(means, "mean")


def estimates_of(edges: DataFrame, name: str, p: Plan, reps: int = 1) -> DataFrame:
    """Copies of a small pattern, a row per repetition: each sample's count by labelled joins over p^vertices R."""
    from . import patterns

    pattern = patterns.NAMED[name]
    sent = materialize(assign(edges, p, reps))
    fit = sent.join(sizes(sent, p, reps).where("kept").select("rep", "i"), ["rep", "i"], "left_semi")
    labelled = patterns.embeddings(fit, pattern, ("rep", "i"))
    out = scaled(sent, labelled.select("rep", "i"), p, reps, pattern.n)
    return out.withColumn("estimate", F.col("estimate") / pattern.automorphisms()).withColumn("hits", F.expr(f"hits div {pattern.automorphisms()}"))


def estimate_pattern(edges: DataFrame, name: str, p: Plan, reps: int = 1) -> DataFrame:
    """The median over repetitions of a pattern's estimates."""
    return lower_median(estimates_of(edges, name, p, reps), "estimate")


def load_profile(edges: DataFrame, p: Plan, reps: int = 1) -> DataFrame:
    """Per sample: edges, those with both ends light (degree under k/p), heavy vertices, and the space."""
    heavy = degrees(edges).where(F.col("deg") >= p.k / p.p).select("v", F.lit(1).alias("h"))
    sent = assign(edges, p, reps)
    x = sent.join(heavy.select(F.col("v").alias("src"), F.col("h").alias("a")), "src", "left").join(heavy.select(F.col("v").alias("dst"), F.col("h").alias("b")), "dst", "left")
    light = F.count_if(F.col("a").isNull() & F.col("b").isNull())
    return x.groupBy("rep", "i").agg(F.count("*").alias("edges"), light.alias("light_edges")).withColumn("space", F.lit(p.space).cast("long"))


def copies_per_edge(edges: DataFrame, p: Plan) -> DataFrame:
    """How many machines each edge is sent to: copies, edges."""
    z = assign(edges, p).groupBy("src", "dst").agg(F.count("*").alias("copies"))
    return edges.join(z, ["src", "dst"], "left").groupBy(F.coalesce("copies", F.lit(0)).alias("copies")).agg(F.count("*").alias("edges"))


def repetitions(n: int) -> int:
    """100 ln n, the number of repetitions whose median the guarantee is about."""
    return math.ceil(100 * math.log(max(2, n)))


def for_graph(edges: DataFrame, **options) -> Plan:
    """The plan of this graph (edges: rows, or a packed table), whose ids must not be negative (model.renumbered gives such). An explicit plan without a space gets the mean of a sample's edges plus four
    standard deviations: p^2 m edges are expected, and edges that share a vertex come together more often.
    By Chebyshev fewer than one sample in 16 overflows, whatever the size or the skew of the graph."""
    deg = materialize(blocks.degrees_of(edges)) if "n" in edges.columns else degrees(edges)
    n, twice, least, most = deg.agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0)), F.min("v"), F.max("v")).first()
    m = twice // 2
    if least is not None and least < 0:
        raise ValueError("vertex ids are negative: number the vertices with model.renumbered")
    options = {"ids": 1 + (most or 0)} | options
    if m and options.get("mode") == "explicit" and options.get("space") is None and options.get("p") is not None:
        p = options["p"]
        shared = deg.agg(F.sum((F.col("deg") * (F.col("deg") - 1)).cast("double"))).first()[0]
        variance = m * p**2 * (1 - p**2) + shared * p**3 * (1 - p)
        options["space"] = min(m, math.ceil(p**2 * m + 4 * math.sqrt(variance)))
    return plan(n, m, **options)
