"""Arrow functions and table functions for what built-in expressions don't cover."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import hashing, patterns, peel
from ..session import ship


def kwise61(coeffs: list[int]):
    """Arrow function of a column: the polynomial modulo 2^61 - 1 (keys of any size)."""

    @F.pandas_udf("long")
    def polynomial(x: pd.Series) -> pd.Series:
        return pd.Series(hashing.kwise_values(x.to_numpy() % hashing.P61, coeffs, hashing.P61).astype("int64"))

    return polynomial


def local_triangles(sent: DataFrame) -> DataFrame:
    """(rep, i, hits): one machine counts the triangles of its own sample in memory; samples are bounded by S."""

    def count(group: pa.Table) -> pa.Table:
        out: dict[int, set[int]] = {}
        for s, d in zip(group["src"].to_pylist(), group["dst"].to_pylist()):
            out.setdefault(s, set()).add(d)
        n = sum(len(out[s] & out[d]) for s in out for d in out[s] if d in out)
        return pa.table({"rep": group["rep"][:1].cast(pa.int32()), "i": group["i"][:1], "hits": pa.array([n], pa.int64())})

    ship(sent.sparkSession)
    return sent.groupBy("rep", "i").applyInArrow(count, "rep int, i long, hits long")


class _Orientations:
    def eval(self, name: str):
        for k, o in enumerate(patterns.orientations(patterns.NAMED[name])):
            yield k, " ".join(f"{x}>{y}" for x, y in o.arcs), o.aut, len(o.order)


class _Pairs:
    def eval(self, values: list):
        v = sorted(set(values or []))
        for i, a in enumerate(v):
            for b in v[i + 1 :]:
                yield a, b


class _Schedule:
    def eval(self, kind: str, g0: float, rounds: int):
        gamma = peel.schedule(kind, g0, g0)
        for i in range(rounds):
            yield i, float(gamma(i))


def register(spark: SparkSession) -> None:
    """SQL names: orientations(pattern), pairs(array), peel_schedule(kind, start, rounds), kwise31(x, seed)."""
    ship(spark)
    spark.udtf.register("orientations", F.udtf(_Orientations, returnType="k int, arcs string, automorphisms int, tree int"))
    spark.udtf.register("pairs", F.udtf(_Pairs, returnType="a bigint, b bigint"))
    spark.udtf.register("peel_schedule", F.udtf(_Schedule, returnType="round int, gamma double"))


def kwise31_sql(x: str, k: int, seed: int) -> str:
    return hashing.kwise_sql(x, hashing.coefficients(k, seed))
