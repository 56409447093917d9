"""Sharding by a k-d tree: nodes are split at weighted medians along their widest metadata dimension.

Dimensions are source, language, size and id, each a whole-number key: 20 bits of the value, then 22 bits
of the text's hash, then 20 bits of the id's hash. Size and id are as wide in a node as their range there to the
range of all rows; source and language, which have no order, as the number of their values there to that of all rows.
Equal texts take the least source, language and id of their group, so they lie together and a cut goes through a
group only if it is too heavy to stay whole. A node of k shards is cut where its bytes stand k // 2 to the rest.
The cut is found by descending the key's bits, 12 at a time, for all nodes of a level in one job: bytes are summed by
(node, bucket), at most 4096 buckets a node, and one row a node comes back: the bucket that holds the median. It stops
when that bucket is too light to matter. Cuts go to the rows as arrays in the plan of one value per node of a level,
above 1024 nodes as broadcast tables, so what is sent and collected is bounded by the number of shards.

Texts are read once; the tree works on a narrow table in the shared folder, written again after each level. Slots are numbered within
(shard, id-hash) parts whose offsets come from counts, so no task gathers a shard.

Defined cases: null text has 0 bytes and crc32 0; null source, language or id are values of their own; rows
equal in id and text share all keys and are not cut apart; an empty table gives no rows; further columns
are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import join_heavy, materialize

SHARDS, OVERHEAD = 40, 16
DIMENSIONS = ("source", "lang", "size", "id")
NOMINAL = ("source", "lang")
BITS, OWN_BITS, STEP = 62, 20, 12  # all, those of the id alone, those of one job
TOLERANCE = 0.001  # of a shard's bytes: lighter buckets need no further look
GROUP_TOLERANCE = 0.01  # groups of equal texts up to this share of a shard stay whole at a cut
PART_ROWS = 500_000
INLINE = 1024  # nodes whose values are arrays in the plan


@dataclass
class Node:
    """A leaf has shard numbers first .. first + count - 1 still to divide; a cut node has a dimension."""

    first: int
    count: int
    path: int
    dim: str | None = None
    cut: int = 0
    sides: list[Node] = field(default_factory=list)

    def leaves(self) -> list[Node]:
        return [self] if self.dim is None else [x for s in self.sides for x in s.leaves()]


def _look_up(rows: DataFrame, nodes: list[int], columns: dict[str, tuple[str, list]]) -> DataFrame:
    """rows with the values of their node (column `node`), null at other nodes; columns: name, its type and a value per node.

    Nodes whose numbers lie within INLINE of each other give arrays in the plan, more a broadcast table.
    """
    low, high = min(nodes), max(nodes)
    if high - low < INLINE:
        at = [n - low for n in nodes]
        for name, (kind, values) in columns.items():
            known = dict(zip(at, values))
            cells = ", ".join("null" if i not in known else repr(known[i]) + ("D" if kind == "double" else "") for i in range(high - low + 1))
            rows = rows.withColumn(name, F.get(F.expr(f"cast(array({cells}) as array<{kind}>)"), (F.col("node") - low).cast("int")))
        return rows
    kinds = {"double": pa.float64(), "int": pa.int32(), "bigint": pa.int64()}
    table = pa.table({"node": pa.array(nodes, pa.int64()), **{k: pa.array(v, kinds[t]) for k, (t, v) in columns.items()}})
    return rows.join(F.broadcast(rows.sparkSession.createDataFrame(table)), "node", "left")


def _key(dim: str) -> Column:
    """The key of the dimension whose number is in a column."""
    return F.element_at(F.array(*[F.col(f"k_{d}") for d in DIMENSIONS]), F.col(dim) + 1)


def descend(rows: DataFrame, cut: list[Node]) -> DataFrame:
    """rows whose `node` is one of the nodes go to the side of its cut."""
    rows = _look_up(rows, [n.path for n in cut], {"dim": ("int", [DIMENSIONS.index(n.dim) for n in cut]), "cut": ("bigint", [n.cut for n in cut])})
    down = 2 * F.col("node") + (_key("dim") >= F.col("cut")).cast("long")
    return rows.withColumn("node", F.when(F.col("dim").isNull(), F.col("node")).otherwise(down)).drop("dim", "cut")


def points(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32 and one key per dimension; equal texts get the least values of their group."""
    text = F.coalesce(F.col("text"), F.lit(""))
    flat = materialize(
        docs.select(
            "doc_id",
            (F.octet_length(text).cast("long") + OVERHEAD).alias("size"),
            F.crc32(text.cast("binary")).cast("long").alias("text_crc32"),
            F.xxhash64(text).alias("text_hash"),
            F.coalesce("source", F.lit("")).alias("source"),
            F.coalesce("lang", F.lit("")).alias("lang"),
        )
    )
    group = ["text_hash", "size"]
    least = [F.min(c).alias(f"g_{d}") for c, d in (("source", "source"), ("lang", "lang"), ("doc_id", "id"))]
    places = materialize(flat.groupBy(*group).agg(F.count("*").alias("rows"), *least).where("rows > 1"))

    def key(value: Column) -> Column:
        high = F.shiftleft(F.least(F.greatest(value, F.lit(0)), F.lit((1 << 20) - 1)).cast("long"), BITS - 20)
        text = F.shiftleft(F.pmod("text_hash", F.lit(1 << 22)), OWN_BITS)
        return high.bitwiseOR(text).bitwiseOR(F.pmod(F.xxhash64("doc_id"), F.lit(1 << OWN_BITS)))

    def named(col: str) -> Column:
        return F.pmod(F.xxhash64(col), F.lit(1 << 20))

    own = [F.when(F.col("rows_").isNotNull(), F.col(f"g_{d}")).otherwise(F.col(c)).alias(f"g_{d}") for c, d in (("source", "source"), ("lang", "lang"), ("doc_id", "id"))]
    joined = join_heavy(flat, places.withColumn("rows_", F.col("rows")), group, "rows", flat.count())
    return joined.select("doc_id", "size", "text_crc32", "text_hash", *own).select(
        "doc_id",
        "size",
        "text_crc32",
        key(named("g_source")).alias("k_source"),
        key(named("g_lang")).alias("k_lang"),
        key(F.floor(F.log2(F.col("size").cast("double")) * 32768)).alias("k_size"),
        key(F.pmod(F.coalesce("g_id", F.lit(-1)), F.lit(1 << 20))).alias("k_id"),
    )


def grow(rows: DataFrame, shards: int = SHARDS, tolerance: float = TOLERANCE) -> tuple[Node, DataFrame]:
    """The tree over points(), from jobs that return a row per node, and the rows with `node`, the number of their leaf.

    Rows are written again after each level, so a job finds its node beside the keys.
    """
    keys = {d: F.col(f"k_{d}") for d in DIMENSIONS}

    def widths():
        for d, k in keys.items():
            yield (F.approx_count_distinct(F.shiftright(k, BITS - 20)) - 1 if d in NOMINAL else F.max(k) - F.min(k)).alias(d)

    first = rows.agg(F.sum("size").alias("all"), *widths()).first()
    root, at = Node(0, shards, 1), rows.withColumn("node", F.lit(1).cast("long"))
    if not first["all"]:
        return root, at
    enough = tolerance * first["all"] / shards
    while todo := [n for n in root.leaves() if n.count > 1]:
        spread = {r["node"]: r for r in at.groupBy("node").agg(F.sum("size").alias("w"), *widths()).collect()}
        goal, base, prefix, chosen = {}, {}, {}, {}
        for n in todo:
            r = spread.get(n.path)
            chosen[n.path] = max(DIMENSIONS, key=lambda d: r[d] / max(1, first[d])) if r else DIMENSIONS[0]
            goal[n.path], base[n.path], prefix[n.path] = (r["w"] if r else 0) * (n.count // 2) / n.count, 0, 0
        active, shift, cuts = [n.path for n in todo if n.path in spread], BITS, {n.path: 0 for n in todo}
        while active:
            step = min(STEP, shift - OWN_BITS if shift > OWN_BITS else shift)
            state = {
                "dim": ("int", [DIMENSIONS.index(chosen[p]) for p in active]),
                "prefix": ("bigint", [prefix[p] for p in active]),
                "base": ("bigint", [base[p] for p in active]),
                "goal": ("double", [goal[p] for p in active]),
            }
            part = _look_up(at, active, state)
            part = part.where(F.shiftright(_key("dim"), shift) == F.col("prefix"))
            shift -= step
            sums = part.groupBy("node", F.shiftright(_key("dim"), shift).alias("bucket")).agg(F.sum("size").alias("w"), F.first("base").alias("base"), F.first("goal").alias("goal"))
            upto = F.sum("w").over(Window.partitionBy("node").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))
            middle = sums.withColumn("upto", F.col("base") + upto).where("upto > goal and upto - w <= goal")
            for r in middle.select("node", "bucket", "w", "upto").collect():
                p, w = r["node"], r["w"]
                base[p], prefix[p] = r["upto"] - w, r["bucket"]
                if shift == 0 or w <= enough or shift == OWN_BITS and w <= enough * GROUP_TOLERANCE / TOLERANCE:
                    active.remove(p)
                    after = base[p] + w - goal[p] < goal[p] - base[p]  # the nearer side of the last bucket
                    cuts[p] = (prefix[p] + after) << shift
        for n in todo:
            half = n.count // 2
            n.dim, n.cut = chosen[n.path], cuts[n.path]
            n.sides = [Node(n.first, half, 2 * n.path), Node(n.first + half, n.count - half, 2 * n.path + 1)]
        at = materialize(descend(at, todo))
    return root, at


def shard(docs: DataFrame, shards: int | None = SHARDS, target_bytes: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot; with target_bytes as many shards as the bytes ask for."""
    rows = materialize(points(docs))
    count, total = rows.agg(F.count("*"), F.sum("size")).first()
    if target_bytes:
        shards = max(1, -(-(total or 0) // target_bytes))
    tree, at = grow(rows, shards)
    leaves = tree.leaves()
    named = _look_up(at, [n.path for n in leaves], {"shard": ("bigint", [n.first for n in leaves])})
    parts = max(8, -(-count // (shards * PART_ROWS)))
    part = F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(parts)).alias("part")
    placed = named.select("doc_id", "size", "text_crc32", "shard", part)
    counts = placed.groupBy("shard", "part").count()
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("shard", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("offset"))
    within = F.row_number().over(Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size")) - 1
    return placed.withColumn("within", within).join(offsets, ["shard", "part"]).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("offset") + F.col("within")).alias("slot")
    )
