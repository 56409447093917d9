"""The graph model: canonical edges src < dst, arcs both ways, degrees, induced subgraphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import materialize


def require_schema(edges: DataFrame) -> DataFrame:
    missing = {"src", "dst"} - set(edges.columns)
    if missing:
        raise ValueError(f"an edge table has columns src and dst; {sorted(missing)} missing")
    return edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))


def ends(pairs: DataFrame) -> DataFrame:
    """Edges src < dst, maybe repeated; null ends and loops go."""
    e = require_schema(pairs).where("src is not null and dst is not null and src <> dst")
    return e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))


def canonical(pairs: DataFrame) -> DataFrame:
    """Distinct edges src < dst; null ends, loops and repeats go."""
    return ends(pairs).distinct()


def dirt(pairs: DataFrame) -> DataFrame:
    """How many rows canonical() drops, by reason."""
    e = require_schema(pairs)
    good = F.col("src").isNotNull() & F.col("dst").isNotNull()
    edge = F.when(good & (F.col("src") != F.col("dst")), F.struct(F.least("src", "dst"), F.greatest("src", "dst")))
    return e.agg(
        F.count_if(~good).alias("null_ends"),
        F.count_if(good & (F.col("src") == F.col("dst"))).alias("loops"),
        (F.count(edge) - F.count_distinct(edge)).alias("repeats"),
    )


def arcs(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionAll(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def degrees(edges: DataFrame) -> DataFrame:
    return arcs(edges).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))


def numbers(vertices: DataFrame, parts: int = 64) -> DataFrame:
    """v, k: the distinct ids (column v) numbered 0, 1, ... in their order. Ranges of ids are numbered side by side and
    shifted by the counts of the ranges before."""
    v = vertices.select("v").distinct().repartitionByRange(parts, "v")
    v = materialize(v.withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shift = v.groupBy("part").count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("shift"))
    within = F.row_number().over(Window.partitionBy("part").orderBy("v")) - 1
    number = v.withColumn("within", within).join(F.broadcast(shift), "part").select("v", (F.col("shift") + F.col("within")).alias("k"))
    return materialize(number)


def renumbered(edges: DataFrame, parts: int = 64) -> DataFrame:
    """The graph with its vertices numbered 0, 1, ... in the order of their ids."""
    number = numbers(arcs(edges).select(F.col("src").alias("v")), parts)
    e = edges.join(number.select(F.col("v").alias("src"), F.col("k").alias("a")), "src").join(number.select(F.col("v").alias("dst"), F.col("k").alias("b")), "dst")
    return e.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    v = vertices.select("v")
    e = edges.join(v.withColumnRenamed("v", "src"), "src", "left_semi")
    return e.join(v.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")


def size(edges: DataFrame) -> DataFrame:
    """n and m in one row."""
    return degrees(edges).agg(F.count("*").alias("n"), F.coalesce((F.sum("deg") / 2).cast("long"), F.lit(0)).alias("m"))
