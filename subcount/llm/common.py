"""Shared helpers of the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..session import ship
from ..storage import materialize  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def map_columns(
    df: DataFrame,
    columns: list[str],
    schema: str | T.StructType,
    make: Callable[[], Callable[[dict[str, list]], Iterator[dict[str, list]]]],
) -> DataFrame:
    """Run a per-task function over Arrow batches of the named columns, as Python lists.

    make() is called once per task; what it returns takes {column: values} and yields the same of the
    result. If it has a method finish(), that is called after the last batch for what is left.
    """
    kind = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(kind)

    def run(batches):
        step = make()
        for batch in batches:
            for out in step(dict(zip(columns, (c.to_pylist() for c in batch.columns)))):
                yield pa.RecordBatch.from_pydict(out, schema=arrow)
        if hasattr(step, "finish"):
            for out in step.finish():
                yield pa.RecordBatch.from_pydict(out, schema=arrow)

    ship(df.sparkSession)
    return df.select(*columns).mapInArrow(run, kind)


def rewrite_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]]) -> DataFrame:
    """A narrow Arrow pass that keeps df's schema: rows are dropped or values replaced, all columns stay."""

    def run(batches):
        step = make()
        for batch in batches:
            yield step(batch)

    ship(df.sparkSession)
    return df.mapInArrow(run, df.schema)


def join_heavy(rows: DataFrame, groups: DataFrame, keys: list[str], weight: str, total: int, parts: int = 1000) -> DataFrame:
    """rows left-joined to groups, one row per key whose `weight` is the number of rows that may carry it.

    At most `parts` groups weigh more than total / parts, whatever the data: those are broadcast, so no key
    that goes through the shuffle holds more than one part of the rows.
    """
    more = [c for c in groups.columns if c not in (*keys, weight)]
    is_heavy = F.col(weight) * parts > max(1, total)
    heavy = groups.where(is_heavy).select(*keys, *more, F.lit(True).alias("heavy_"))
    marked = rows.join(F.broadcast(heavy), keys, "left")
    light = marked.where("heavy_ is null").select(*rows.columns).join(groups.where(~is_heavy).select(*keys, *more), keys, "left")
    return marked.where("heavy_").select(*rows.columns, *more).unionByName(light.select(*rows.columns, *more))


def maybe_among(ids: DataFrame, most_bits: int = 1 << 27) -> Callable[[Column], Column]:
    """A test that holds for each of the ids (one long column) and for few others: a Bloom filter of 16 bits an id, at
    most `most_bits` (16 MB), above which more others pass. What passes is to be looked up; what doesn't needs no
    shuffle. Bits are set where the ids are and come to the driver as words, bounded by the size of the filter."""
    id_ = ids.columns[0]
    size = 1 << 16
    while size < most_bits and size < 16 * ids.count():
        size *= 2
    h = F.xxhash64(id_)
    low, high = h.bitwiseAND(F.lit(0xFFFFFFFF)), F.shiftrightunsigned(h, 32).bitwiseOR(F.lit(1))
    places = F.explode(F.array(*[(low + k * high).bitwiseAND(F.lit(size - 1)) for k in range(6)]))
    bit = F.expr("shiftleft(1L, cast(place & 63 as int))")
    words = ids.select(places.alias("place")).groupBy(F.shiftright("place", 6).alias("word")).agg(F.bit_or(bit).alias("bits")).toArrow()
    table = np.zeros(size >> 6, np.int64)
    table[words["word"].to_numpy()] = words["bits"].to_numpy()
    shared = ids.sparkSession.sparkContext.broadcast(table)

    @F.arrow_udf("boolean")
    def passes(hashes: pa.Array) -> pa.Array:
        h, bits = hashes.to_numpy(zero_copy_only=False).view(np.uint64), shared.value.view(np.uint64)
        low, high = h & np.uint64(0xFFFFFFFF), (h >> np.uint64(32)) | np.uint64(1)
        ok = np.ones(len(h), bool)
        for k in range(6):
            place = (low + np.uint64(k) * high) & np.uint64(size - 1)
            ok &= (bits[place >> np.uint64(6)] >> (place & np.uint64(63)) & np.uint64(1)) > 0
        return pa.array(ok)

    return lambda col: col.isNotNull() & passes(F.xxhash64(col))


def give_back(model):
    """model; before, memory that its fit has freed goes back to the system, where the C library can do that."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)
    return model


def remainder(doc_id, n: int) -> int:
    """crc32 of the id as text, modulo n: the split rule of the learned operators."""
    return zlib.crc32(str(doc_id).encode()) % n


def remainder_col(col: str, n: int):
    return F.pmod(F.crc32(F.col(col).cast("string").cast("binary")), F.lit(n))


def sample_rows(df: DataFrame, key: str, bound: int) -> list:
    """At most `bound` rows, those with the smallest hash of the key: the same rows on every run.

    Keys are chosen first, so tasks send the driver keys only and then the rows of the chosen ones.
    """
    keys = df.select(key).where(F.col(key).isNotNull()).orderBy(F.xxhash64(F.col(key).cast("string")), F.col(key)).limit(bound)
    chosen = df.sparkSession.createDataFrame(keys.collect(), keys.schema).distinct()
    rows = df.join(F.broadcast(chosen), key, "left_semi").limit(bound).collect()
    return sorted(rows, key=lambda r: r[key])
