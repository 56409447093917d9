"""Tables in the folder all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

CLEAN_KEY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder the cluster names; a temporary one only where all executors are this machine (tests)."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named is None:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = getattr(checkpoint_dir, "own", None)
        if named is None:
            named = checkpoint_dir.own = tempfile.mkdtemp(prefix="subcount-")
    return named.rstrip("/")


def materialize(df: DataFrame) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage, survives lost executors. The shuffle files of
    the write are removed once it ends, where the session leaves Spark's default."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark)}/stage-{uuid.uuid4().hex}"
    kept = spark.conf.get(CLEAN_KEY, None)
    spark.conf.set(CLEAN_KEY, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(CLEAN_KEY) if kept is None else spark.conf.set(CLEAN_KEY, kept)
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)
    return spark.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Remove the files of a table that materialize has written and that nothing reads any more."""
    spark = df.sparkSession
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
