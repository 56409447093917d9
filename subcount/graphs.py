"""Graphs derived from the given tables; each gives canonical edges."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .model import canonical, renumbered
from .session import ship
from .storage import materialize

DAY = 86400


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _lines(spark, d):
    l = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return l.join(o, l.l_orderkey == o.o_orderkey)


def _edges(df, a, b):
    return df.select(F.expr(a).alias("src"), F.expr(b).alias("dst"))


def tripartite_pairs(spark: SparkSession, d: str) -> DataFrame:
    x = _lines(spark, d).select((F.col("o_custkey") * 3).alias("c"), (F.col("l_partkey") * 3 + 1).alias("p"), (F.col("l_suppkey") * 3 + 2).alias("s"))
    pair = F.explode(F.array(*[F.struct(F.col(a).alias("src"), F.col(b).alias("dst")) for a, b in (("c", "p"), ("c", "s"), ("p", "s"))]))
    return x.select(pair.alias("e")).select("e.src", "e.dst")


def tripartite(spark: SparkSession, d: str) -> DataFrame:
    return canonical(tripartite_pairs(spark, d))


def custpart(spark: SparkSession, d: str) -> DataFrame:
    return canonical(_edges(_lines(spark, d), "o_custkey * 3", "l_partkey * 3 + 1"))


def _together(spark, d, col):
    """Pairs of an order's lines, whose values are collected, so that a line is dealt once."""
    x = table(spark, d, "lineitem").select("l_orderkey", F.col(col).alias("x")).where("l_orderkey is not null and x is not null")
    order = x.groupBy("l_orderkey").agg(F.collect_set("x").alias("all")).where("size(`all`) > 1")
    first = order.select("all", F.explode("all").alias("src"))
    return first.select("src", F.explode(F.filter("all", lambda y: y > F.col("src"))).alias("dst"))


def copurchase_pairs(spark: SparkSession, d: str) -> DataFrame:
    return _together(spark, d, "l_partkey")


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    return canonical(copurchase_pairs(spark, d))


def cosupply_pairs(spark: SparkSession, d: str) -> DataFrame:
    return _together(spark, d, "l_suppkey")


def cosupply(spark: SparkSession, d: str) -> DataFrame:
    return canonical(cosupply_pairs(spark, d))


def near_in_time(rows: DataFrame, key: str, who: str, at: str, reach: int) -> DataFrame:
    return canonical(near_pairs(rows, key, who, at, reach))


def near_pairs(rows: DataFrame, key: str, who: str, at: str, reach: int) -> DataFrame:
    """Pairs, maybe repeated, of different `who` with one key whose whole-number times differ by at most `reach`.

    Rows are dealt once, to the bucket of their key and time and, where they are within reach of its start, as later
    ends only to the bucket before; a bucket is a few times as long as the reach, so few rows are dealt twice. Repeats
    of a row go as the buckets are collected.
    """
    long = 4 * (reach + 1)
    r = rows.select(F.col(key).alias("k"), F.col(who).alias("x"), F.col(at).alias("t")).where("k is not null and x is not null and t is not null")
    into = lambda t: F.pmod(F.col(t), F.lit(long))
    b = ((F.col("t") - into("t")) / long).cast("long")
    dealt = r.withColumn("b", F.explode(F.when(into("t") < reach, F.array(b, b - 1)).otherwise(F.array(b))))
    bucket = dealt.groupBy("k", "b").agg(F.collect_set(F.struct("t", "x")).alias("all")).where("size(`all`) > 1")
    first = bucket.select("b", "all", F.explode("all").alias("e")).where(F.col("e.t") - into("e.t") == F.col("b") * long)
    near = F.filter("all", lambda y: (y["t"] >= F.col("e.t")) & (y["t"] - F.col("e.t") <= reach) & (y["x"] != F.col("e.x")))
    hit = first.select(F.col("e.x").alias("src"), F.explode(F.transform(near, lambda y: y["x"])).alias("dst"))
    return hit


def copart30_pairs(spark: SparkSession, d: str) -> DataFrame:
    x = _lines(spark, d).withColumn("day", F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01")))
    return near_pairs(x, "l_partkey", "o_custkey", "day", 30)


def copart30(spark: SparkSession, d: str) -> DataFrame:
    return canonical(copart30_pairs(spark, d))


def corun_pairs(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return near_pairs(e, "event_type", "user_id", "us", 60_000_000)


def corun(spark: SparkSession, d: str) -> DataFrame:
    return canonical(corun_pairs(spark, d))


def trade(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
    x = _lines(spark, d).select("o_custkey", "l_suppkey").distinct().join(c, "o_custkey").join(s, "l_suppkey")
    return canonical(_edges(x, "c_nationkey", "s_nationkey"))


def vecsim_pairs(spark: SparkSession, d: str, least: float = 0.3, block: int = 4096) -> DataFrame:
    """Cosine at least `least`. Rows are dealt once, to blocks by a hash, and written with a block in a row; each pair of
    blocks, read again, is one matrix product, and only pairs that are near enough become rows."""
    v = table(spark, d, "embeddings").select(F.col("vec_id").cast("long").alias("x"), F.col("embedding").alias("v")).where("x is not null and v is not null")
    single = v.schema["v"].dataType.elementType.simpleString() == "float"
    kind = np.float32 if single else np.float64
    blocks = max(1, -(-v.count() // block))
    own = F.pmod(F.xxhash64("x"), F.lit(blocks)).cast("int")

    def pack(key: tuple, group: pa.Table) -> pa.Table:
        rows = np.array(group["v"].to_pylist(), np.float64).astype(kind)
        return pa.table({"i": [key[0].as_py()], "x": [group["x"].to_numpy().tobytes()], "v": [rows.tobytes()]}, schema=pa.schema([("i", pa.int32()), ("x", pa.binary()), ("v", pa.binary())]))

    def near(batches):
        for batch in batches:
            for i, j, *both in zip(*(batch[name].to_pylist() for name in ("i", "j", "x", "y", "v", "w"))):
                x, y = (np.frombuffer(z, np.int64) for z in both[:2])
                a, b = (np.frombuffer(z, kind).reshape(len(n), -1).astype(np.float64) for z, n in zip(both[2:], (x, y)))
                for z in (a, b):
                    z /= np.maximum(np.sqrt((z * z).sum(1, keepdims=True)), 1e-300)
                for s in range(0, len(x), 1024):
                    p, q = np.nonzero(a[s : s + 1024] @ b.T >= least)
                    src, dst = x[s + p], y[q]
                    keep = src < dst if i == j else src != dst
                    yield pa.RecordBatch.from_pydict({"src": src[keep], "dst": dst[keep]})

    ship(spark)
    held = materialize(v.withColumn("own", own).groupBy("own").applyInArrow(pack, "i int, x binary, v binary"))
    other = held.select(F.col("i").alias("j"), F.col("x").alias("y"), F.col("v").alias("w"))
    pairs = held.crossJoin(other).where("i <= j").select("i", "j", "x", "y", "v", "w")
    return pairs.mapInArrow(near, "src long, dst long")


def vecsim(spark: SparkSession, d: str, least: float = 0.3, block: int = 4096) -> DataFrame:
    return canonical(vecsim_pairs(spark, d, least, block))


def lexical_words(spark: SparkSession, d: str) -> DataFrame:
    """Adjacent different words (a, b) of a turn, lower-cased after the split."""
    w = F.transform(F.filter(F.split("text", "[^A-Za-z]+"), lambda x: x != ""), F.lower)
    pairs = table(spark, d, "conversations").select(w.alias("w")).where("size(w) > 1")
    zipped = F.arrays_zip(F.slice("w", F.lit(1), F.size("w") - 1).alias("a"), F.slice("w", F.lit(2), F.size("w") - 1).alias("b"))
    return pairs.select(F.explode(zipped).alias("p")).select("p.a", "p.b").where("a <> b")


def named(pairs: DataFrame) -> DataFrame:
    """Edges between text keys a and b: 64-bit hashes are the ids (check with collisions())."""
    return canonical(pairs.select(F.xxhash64("a").alias("src"), F.xxhash64("b").alias("dst")))


def dictionary(pairs: DataFrame) -> DataFrame:
    keys = pairs.select(F.col("a").alias("key")).unionAll(pairs.select(F.col("b").alias("key"))).distinct()
    return keys.select(F.xxhash64("key").alias("id"), "key")


def collisions(dictionary: DataFrame) -> DataFrame:
    return dictionary.groupBy("id").agg(F.count_distinct("key").alias("keys")).where("keys > 1")


def lexical(spark: SparkSession, d: str) -> DataFrame:
    return named(lexical_words(spark, d))


def document_lines(spark: SparkSession, d: str, name: str = "documents", key: str = "doc_id") -> DataFrame:
    t = table(spark, d, name).select(F.col(key).alias("x"), F.explode(F.split("text", "\n")).alias("line"))
    return t.where(F.length("line") >= 20).distinct()


def sharedline(spark: SparkSession, d: str, reach: int = 8, run: int = 1 << 16) -> DataFrame:
    """Two documents that hold the same line and are at most `reach` apart in the order of the ids of all documents
    with it. Every line takes part, however frequent; edges are at most `reach` times the (document, line) pairs, and
    a line's documents are connected. A line's ids are kept in runs of ids, so no task sorts a frequent line; a run is
    followed by the first ids of the runs after it. Only ids and hashes of lines are shuffled."""
    t = table(spark, d, "documents").select(F.col("doc_id").alias("x"), F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= 20)
    x = t.select("x", F.xxhash64("line").alias("k"), F.xxhash64("line", F.lit(1)).alias("l")).where("x is not null")
    runs = x.groupBy("k", "l", F.floor(F.col("x") / run).alias("run")).agg(F.sort_array(F.collect_set("x")).alias("own"))
    after = Window.partitionBy("k", "l").orderBy("run").rowsBetween(1, reach)
    more = F.slice(F.flatten(F.collect_list(F.slice("own", 1, reach)).over(after)), 1, reach)
    both = runs.withColumn("all", F.concat("own", more)).where("size(`all`) > 1").select("all", F.size("own").alias("n"))
    apart = F.explode(F.sequence(F.lit(1), F.least(F.lit(reach), F.size("all") - 1))).alias("apart")
    spread = both.select("all", apart, "n").withColumn("n", F.least("n", F.size("all") - F.col("apart")))
    pair = F.arrays_zip(F.slice("all", F.lit(1), F.col("n")).alias("src"), F.slice("all", F.col("apart") + 1, F.col("n")).alias("dst"))
    return canonical(spread.select(F.explode(pair).alias("e")).select("e.src", "e.dst"))


def quality(spark: SparkSession, d: str) -> DataFrame:
    from .model import induced

    good = table(spark, d, "labels").where("quality = 1").select(F.col("doc_id").alias("v")).distinct()
    return induced(sharedline(spark, d), good)


def benchhit(spark: SparkSession, d: str) -> DataFrame:
    x, y = document_lines(spark, d), document_lines(spark, d, "benchmark", "item_id").withColumnRenamed("x", "y")
    return canonical(x.join(y, "line").select((F.col("x") * 2).alias("src"), (F.col("y") * 2 + 1).alias("dst")))


def hyperlink(spark: SparkSession, d: str) -> DataFrame:
    href = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))
    x = table(spark, d, "pages").select("page_id", href.alias("href"))
    return named(x.select(F.concat(F.lit("page "), F.col("page_id").cast("string")).alias("a"), F.concat(F.lit("href "), "href").alias("b")))


def geo(spark: SparkSession, d: str) -> DataFrame:
    n, c, s = (table(spark, d, t) for t in ("nation", "customer", "supplier"))
    parts = (
        _edges(n, "cast(n_regionkey as bigint) * 4", "cast(n_nationkey as bigint) * 4 + 1"),
        _edges(c, "cast(c_nationkey as bigint) * 4 + 1", "c_custkey * 4 + 2"),
        _edges(s, "cast(s_nationkey as bigint) * 4 + 1", "s_suppkey * 4 + 3"),
    )
    return canonical(parts[0].unionAll(parts[1]).unionAll(parts[2]))


GRAPHS = {f.__name__: f for f in (tripartite, copurchase, lexical, sharedline, cosupply, copart30, corun, vecsim, trade, custpart, hyperlink, quality, benchhit, geo)}
PAIRS = {"tripartite": tripartite_pairs, "copurchase": copurchase_pairs, "cosupply": cosupply_pairs, "copart30": copart30_pairs, "corun": corun_pairs, "vecsim": vecsim_pairs}
KEYED = ("lexical", "hyperlink")  # ids are hashes of text keys


def numbered(spark: SparkSession, d: str, name: str) -> DataFrame:
    """The graph with ids that hash functions can take: those of text keys are numbered anew."""
    e = GRAPHS[name](spark, d)
    return renumbered(e) if name in KEYED else e


def pairs(spark: SparkSession, d: str, name: str) -> DataFrame:
    """Pairs of which the graph is made, with repeats where they are not taken out on the way (for blocks.stored)."""
    return PAIRS.get(name, GRAPHS[name])(spark, d)
