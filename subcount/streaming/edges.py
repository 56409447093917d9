"""Streams of edges from events: windows, late rows, repeats, interval joins, incremental triangles."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..model import arcs, canonical
from ..storage import checkpoint_dir


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A file stream over a Parquet file or folder of events; ts as a timestamp."""
    schema = spark.read.parquet(path).schema
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    return (s.option("pathGlobFilter", path.rsplit("/", 1)[1]).parquet(path.rsplit("/", 1)[0]) if path.endswith(".parquet") else s.parquet(path)).withColumn("ts", F.col("ts").cast("timestamp"))


def collect_now(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Run what is there now into Parquet in the shared folder and read it back: appended rows; in complete mode the
    table after the last batch; in update mode the last row of each key."""
    spark = stream.sparkSession
    at = f"{checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"
    w = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{at}/state")
    if mode == "append":
        w.format("parquet").option("path", f"{at}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")
    numbers = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={number}")
        numbers.append(number)

    w.foreachBatch(keep).start().awaitTermination()
    if not numbers:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{at}/out/batch={max(numbers)}")
    if not keys:
        raise ValueError("update mode needs the keys whose last rows are kept")
    rows = spark.read.parquet(f"{at}/out")
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*[c for c in stream.columns if c not in keys]), "batch").alias("r"))
    return last.select(*[F.col(c) if c in keys else F.col(f"r.{c}").alias(c) for c in stream.columns])


def tumbling(stream: DataFrame, width: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("events")).select(F.unix_seconds(F.col("w.start")).alias("start_s"), "event_type", "events")


def sliding(stream: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("events")).select(F.unix_seconds(F.col("w.start")).alias("start_s"), "events")


def sessions(stream: DataFrame, gap: str = "1 hour") -> DataFrame:
    s = stream.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
    return s.select("user_id", F.unix_micros(F.col("w.start")).alias("start_us"), "events")


def without_repeats(stream: DataFrame, keys: list[str], delay: str = "365 days") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def in_time(stream: DataFrame, delay: str = "1 hour", width: str = "1 hour") -> DataFrame:
    """Windows that closed, without rows later than the watermark."""
    return stream.withWatermark("ts", delay).groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("events")).select(F.unix_seconds(F.col("w.start")).alias("start_s"), "events")


def interval_edges(stream: DataFrame, seconds: int = 60, delay: str = "1 day") -> DataFrame:
    """Users with events of one type within so many seconds, as (src, dst) pairs. The join is an equality on type and
    time bucket, so a frequent type is spread over its buckets; both sides have watermarks, and the state of a
    bucket goes when they pass its time."""
    bucket = lambda t: F.floor(F.unix_seconds(t) / (seconds + 1))
    a = stream.select(F.col("user_id").alias("x"), F.col("event_type").alias("k"), F.col("ts").alias("t")).withWatermark("t", delay)
    b = stream.select(F.col("user_id").alias("y"), F.col("event_type").alias("l"), F.col("ts").alias("u")).withWatermark("u", delay)
    a = a.withColumn("p", bucket(F.col("t")))
    b = b.withColumn("q", F.explode(F.array(bucket(F.col("u")), bucket(F.col("u")) - 1)))
    near = (F.col("u") >= F.col("t")) & (F.col("u") <= F.col("t") + F.expr(f"interval {seconds} seconds"))
    on = (F.col("k") == F.col("l")) & (F.col("p") == F.col("q")) & near & (F.col("x") != F.col("y"))
    return a.join(b, on).select(F.col("x").alias("src"), F.col("y").alias("dst"))


def degrees_so_far(stream: DataFrame) -> DataFrame:
    """v, degree after each batch of an edge stream (src, dst) for the vertices it touches: arbitrary state per vertex."""
    ends = stream.select(F.explode(F.array("src", "dst")).alias("v"))

    def count(key, batches, state):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"v": [key[0]], "degree": [n]})

    return ends.groupBy("v").applyInPandasWithState(count, "v long, degree long", "degree long", "update", GroupStateTimeout.NoTimeout)


def new_triangles(old: DataFrame, new: DataFrame) -> DataFrame:
    """One row: triangles with a new edge. A triangle with j new edges is found at each of them: weights 1/j."""
    both = arcs(old).withColumn("fresh", F.lit(0)).unionAll(arcs(new).withColumn("fresh", F.lit(1)))
    x = both.select(F.col("src").alias("a"), F.col("dst").alias("c"), F.col("fresh").alias("p"))
    y = both.select(F.col("src").alias("b"), F.col("dst").alias("c"), F.col("fresh").alias("q"))
    hit = new.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(x, "a").join(y, ["b", "c"])
    n = hit.agg(*[F.coalesce(F.sum(F.when(F.col("p") + F.col("q") == k, 1)), F.lit(0)).alias(f"n{k}") for k in range(3)])
    return n.select(F.expr("n0 + n1 div 2 + n2 div 3").alias("triangles"))


class Counter:
    """foreachBatch state in a folder: the new edges and the new triangles of each batch. A batch that is run again
    overwrites its own folders, and a restarted stream goes on from those of the batches before."""

    def __init__(self, spark: SparkSession, at: str):
        self.spark, self.at = spark, at

    def _before(self, number: int) -> DataFrame:
        if not number:
            return self.spark.createDataFrame([], "src long, dst long")
        known = self.spark.read.schema("src long, dst long, batch long").parquet(f"{self.at}/edges")
        return known.where(F.col("batch") < number).select("src", "dst")

    def __call__(self, batch: DataFrame, number: int) -> None:
        old, here = self._before(number), f"{self.at}/edges/batch={number}"
        canonical(batch).join(old, ["src", "dst"], "left_anti").write.mode("overwrite").parquet(here)
        new = self.spark.read.schema("src long, dst long").parquet(here)
        new_triangles(old, new).write.mode("overwrite").parquet(f"{self.at}/counts/batch={number}")

    def total(self) -> DataFrame:
        return self.spark.read.schema("triangles long, batch long").parquet(f"{self.at}/counts").agg(F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))


def incremental_triangles(stream: DataFrame, at: str | None = None) -> DataFrame:
    """One row: triangles after all batches of an edge stream (src, dst); at: the folder of the state."""
    spark = stream.sparkSession
    at = at or f"{checkpoint_dir(spark)}/triangles-{uuid.uuid4().hex}"
    c = Counter(spark, at)
    stream.writeStream.foreachBatch(c).trigger(availableNow=True).option("checkpointLocation", f"{at}/progress").start().awaitTermination()
    return c.total()
