"""Session helpers: make a local session, and let Python workers import this package."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import SparkSession

# Rows of an Arrow batch, unless the session names a number. Spark's 10000 whole texts fill tens of MB in the task's
# off-heap buffers, and again in its worker.
BATCH, SPARKS_BATCH, BATCH_KEY = "1000", "10000", "spark.sql.execution.arrow.maxRecordsPerBatch"
ROOT = str(Path(__file__).resolve().parent.parent)


def ship(spark: SparkSession) -> SparkSession:
    """Put the repository on the Python path of the workers (a cluster submits it with --py-files), and bound what
    they are handed at once."""
    if spark.conf.get(BATCH_KEY, SPARKS_BATCH) == SPARKS_BATCH:
        spark.conf.set(BATCH_KEY, BATCH)
    env = spark.sparkContext.environment
    paths = env.get("PYTHONPATH", "").split(os.pathsep)
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, paths)])
    return spark


def local(cores: int | str = "*", partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session on this machine for tests and the bench."""
    return ship(
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", partitions)
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
