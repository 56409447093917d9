"""Edge sources and sinks: text lists, files of other formats, generated graphs, a Python data source."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model import canonical, numbers
from ..operators import hashing
from ..session import ship


def read_text(spark: SparkSession, path: str, comment: str = "#") -> DataFrame:
    """Pairs of whole numbers, split by blanks, tabs or commas; comment lines and others are skipped."""
    t = spark.read.text(path).where(~F.col("value").startswith(comment))
    part = F.split(F.trim("value"), r"[\s,]+")
    return canonical(t.select(F.try_element_at(part, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(part, F.lit(2)).try_cast("long").alias("dst")))


def read(spark: SparkSession, path: str, kind: str = "parquet", src: str = "src", dst: str = "dst") -> DataFrame:
    if kind == "text":
        return read_text(spark, path)
    options = {"header": True, "inferSchema": False} if kind == "csv" else {}
    t = spark.read.options(**options).format(kind).load(path)
    return canonical(t.select(F.col(src).try_cast("long").alias("src"), F.col(dst).try_cast("long").alias("dst")))


def pairs(spark: SparkSession, rows: list[tuple[int, int]]) -> DataFrame:
    return canonical(spark.createDataFrame(rows, "src long, dst long"))


def write(edges: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] | None = None) -> None:
    w = edges.write.mode("overwrite").format(kind)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed and sorted by src, so rounds start without a shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def run_only(df: DataFrame) -> None:
    """Run the whole plan and keep nothing (timing)."""
    df.write.mode("overwrite").format("noop").save()


def generate(spark: SparkSession, kind: str, n: int, m: int = 0, seed: int = 1, ids: DataFrame | None = None) -> DataFrame:
    """clique, cycle, star, path, grid (n by n), uniform (m random pairs), preferential (m edges a vertex). ids: a table
    that has the numbers of the vertices (uniform: of the pairs) as its column id, in place of made ones."""
    numbered = lambda k: spark.range(k) if ids is None else ids.select("id").where(F.col("id") < k)
    v = numbered(n)
    i = F.col("id")
    if kind == "clique":
        return canonical(v.select(i.alias("src"), F.explode(F.sequence(F.lit(0), i)).alias("dst")))
    if kind == "cycle":
        return canonical(v.select(i.alias("src"), ((i + 1) % n).alias("dst")))
    if kind == "path":
        return canonical(v.where(i > 0).select((i - 1).alias("src"), i.alias("dst")))
    if kind == "star":
        return canonical(v.where(i > 0).select(F.lit(0).alias("src"), i.alias("dst")))
    if kind == "grid":
        at = numbered(n * n)
        right = at.where((i % n) < n - 1).select(i.alias("src"), (i + 1).alias("dst"))
        return canonical(right.unionAll(at.where(i < n * (n - 1)).select(i.alias("src"), (i + n).alias("dst"))))
    c = hashing.coefficients(4, seed)
    if kind == "uniform":
        end = lambda k: hashing.kwise(hashing.checked(2 * i + k, hashing.P31), c) % n
        return canonical(numbered(m).select(end(0).alias("src"), end(1).alias("dst")))
    if kind == "preferential":
        e = v.where(i > 0).select(i.alias("src"), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("k"))
        u = hashing.kwise(hashing.checked(F.col("src") * m + F.col("k"), hashing.P31), c) / F.lit(float(hashing.P31))
        return canonical(e.select("src", F.floor(F.col("src") * u * u).alias("dst")))
    raise ValueError(f"no graph {kind}")


def generate_on(keys: DataFrame, kind: str, m: int = 0, seed: int = 1) -> DataFrame:
    """The generated graph whose vertices are the distinct keys (one column) in their order: a grid takes the largest
    square of them, uniform draws a pair for each."""
    ids = numbers(keys.select(F.col(keys.columns[0]).alias("v")).where("v is not null")).select(F.col("k").alias("id"))
    n = ids.count()
    return generate(keys.sparkSession, kind, math.isqrt(n) if kind == "grid" else n, n if kind == "uniform" else m, seed, ids)


class _Lines(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def _opened(path: str):
    """A file system and a path of it: of a URI, or this machine's."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


class _Reader(DataSourceReader):
    """Byte ranges of text edge lists; a range reads the lines that begin in it. Lines that are no two whole numbers
    are skipped."""

    def __init__(self, options):
        self.path, self.parts = options["path"], int(options.get("parts", 4))

    def partitions(self):
        from pyarrow import fs

        store, at = _opened(self.path)
        info = store.get_file_info(at)
        files = store.get_file_info(fs.FileSelector(at, recursive=True)) if info.type == fs.FileType.Directory else [info]
        files = [f for f in files if f.type == fs.FileType.File and f.size and not f.base_name.startswith(("_", "."))]
        step = max(1, -(-sum(f.size for f in files) // self.parts))
        return [_Lines(f.path, s, min(f.size, s + step)) for f in files for s in range(0, f.size, step)] or [_Lines("", 0, 0)]

    def read(self, partition):
        if not partition.path:
            return
        with _opened(self.path)[0].open_input_file(partition.path) as f:
            at = max(0, partition.start - 1)
            f.seek(at)
            rest, begun = b"", not partition.start  # begun: the next line begins in the range
            while True:
                data = f.read(1 << 20)
                lines = (rest + data).split(b"\n")
                rest = lines.pop() if data else b""
                for line in lines:
                    start, at = at, at + len(line) + 1
                    if begun and start >= partition.end:
                        return
                    part = line.split() if begun else ()
                    begun = True
                    if len(part) >= 2 and part[0].lstrip(b"-").isdigit() and part[1].lstrip(b"-").isdigit():
                        yield int(part[0]), int(part[1])
                if not data:
                    return


class EdgeListSource(DataSource):
    """format("edgelist"): path of a text file or folder (a URI of a store that pyarrow opens, or a folder all executors
    mount), parts."""

    @classmethod
    def name(cls):
        return "edgelist"

    def schema(self):
        return "src bigint, dst bigint"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    ship(spark).dataSource.register(EdgeListSource)
