"""Primitives the methods are made of: repeats, membership, predecessor, replicas, shard keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def count_repeats(df: DataFrame, cols: list[str]) -> DataFrame:
    """Each distinct element and its number: partial and final hash aggregation, one exchange."""
    return df.groupBy(*cols).agg(F.count("*").alias("repeats"))


def count_repeats_tree(df: DataFrame, col: str, parts: int = 8, fanout: int = 4) -> DataFrame:
    """The same over sorted partitions: runs are counted where they lie, runs that cross partitions are merged
    in groups of `fanout` partitions, level by level; a level only sees one run per element and group."""
    laid = df.select(F.col(col).alias("x")).repartitionByRange(parts, "x").withColumn("part", F.spark_partition_id())
    runs = laid.groupBy("part", "x").agg(F.count("*").alias("repeats"))
    width = parts
    while width > 1:
        runs = runs.withColumn("part", F.floor(F.col("part") / fanout)).groupBy("part", "x").agg(F.sum("repeats").alias("repeats"))
        width = -(-width // fanout)
    return runs.select(F.col("x").alias(col), "repeats")


def predecessor(df: DataFrame, order: list[str], tag: str, value: Column, within: list[str] | None = None) -> DataFrame:
    """Adds `before`: the value of the last row tagged 0 at or before each row in the order (ties: 0 first)."""
    w = Window.partitionBy(*(within or [])).orderBy(*order, tag).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn("before", F.last(F.when(F.col(tag) == 0, value), ignorenulls=True).over(w))


def member(queries: DataFrame, members: DataFrame, keys: list[str], how: str = "join") -> DataFrame:
    """The queries, repeats kept, with is_member. how: join (hash or merge join on distinct members) or sort
    (tag both, sort within a key's hash part, look at the last member before)."""
    m = members.select(*keys).distinct()
    if how == "join":
        return queries.join(m.withColumn("hit", F.lit(True)), keys, "left").withColumn("is_member", F.coalesce("hit", F.lit(False))).drop("hit")
    if how != "sort":
        raise ValueError(f"how is join or sort, not {how}")
    both = m.withColumn("tag", F.lit(0)).unionByName(queries.select(*keys).withColumn("tag", F.lit(1)))
    both = both.withColumn("lot", F.pmod(F.xxhash64(*keys), F.lit(1024)))
    found = predecessor(both, keys, "tag", F.struct(*keys), ["lot"])
    return found.where("tag = 1").select(*keys, F.coalesce(F.col("before").eqNullSafe(F.struct(*keys)), F.lit(False)).alias("is_member"))


def replicate(df: DataFrame, x: int, fanout: int | None = None) -> DataFrame:
    """Each row x times with its copy number; with a fan-out in rounds of that many copies each."""
    if fanout is None or fanout >= x:
        return df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(x - 1))).cast("long"))
    out, made = df.withColumn("copy", F.lit(0).cast("long")), 1
    while made < x:
        out = out.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(fanout - 1)))).withColumn("copy", F.col("copy") + F.col("k") * made).drop("k").where(F.col("copy") < x)
        made *= fanout
    return out


def sort_all(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.orderBy(*cols)


def shard_key(other: Column, need: Column, cap: int) -> Column:
    """Salt of a row of a vertex that needs `need` words on machines of `cap` words."""
    return F.pmod(F.xxhash64(other), F.greatest(F.lit(1), F.ceil(need / cap)))


def first_rows(df: DataFrame, keys: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each key."""
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col("_r") <= k).drop("_r")
