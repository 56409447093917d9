"""Globally known hash functions: k-wise independent polynomials, and mixed 64-bit hashes."""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P31 = (1 << 31) - 1
P61 = (1 << 61) - 1


def field(keys: int) -> int:
    """The prime of the least field in which so many keys are different elements."""
    for prime in (P31, P61):
        if keys <= prime:
            return prime
    raise ValueError(f"{keys} keys don't fit 61 bits: number the vertices with model.renumbered")


def checked(v: Column, ids: int) -> Column:
    """v where it is a number from 0 to ids - 1; an error otherwise, as keys would collide."""
    return F.when((v >= 0) & (v < ids), v).otherwise(F.raise_error(F.concat(F.lit(f"a vertex id under {ids} is needed (see model.renumbered), not "), v.cast("string"))).cast("long"))


def pair_key(v: Column, i: Column, ids: int, machines: int) -> Column:
    """A different element of the field for each vertex under `ids` and machine."""
    return checked(v, ids) * machines + i


def times61(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo 2^61 - 1 of uint64 values under it, by halves of 31 bits."""
    low, thirty, full = np.uint64(P31), np.uint64(30), np.uint64(P61)
    a1, a0, b1, b0 = a >> np.uint64(31), a & low, b >> np.uint64(31), b & low
    mid = a1 * b0 + a0 * b1
    s = np.uint64(2) * a1 * b1 + (mid >> thirty) + ((mid & np.uint64((1 << 30) - 1)) << np.uint64(31)) + a0 * b0
    s = (s & full) + (s >> np.uint64(61))
    return np.where(s >= full, s - full, s)


def kwise_values(x: np.ndarray, coeffs: list[int], prime: int) -> np.ndarray:
    """The polynomial's values at whole numbers under the prime."""
    x = x.astype(np.uint64)
    h, p = np.full(x.shape, coeffs[0], np.uint64), np.uint64(prime)
    low, bits = np.uint64(P31), np.uint64(31)
    for c in coeffs[1:]:
        if prime == P31:  # 2^31 is 1: halves are added, twice, in place of a division
            h *= x
            h += np.uint64(c)
            for _ in range(2):
                high = h >> bits
                h &= low
                h += high
        else:
            h = times61(h, x) + np.uint64(c) if prime == P61 else h * x % p + np.uint64(c)
        np.subtract(h, p, out=h, where=h >= p)
    return h


def skips(v: int, p: float, machines: int, seed: int, rep: int) -> np.ndarray:
    """The machines of a vertex, each with probability p, from its own generator: about p machines draws."""
    rng = np.random.default_rng([seed, rep, v & ((1 << 64) - 1)])
    out, at = [], -1
    while at < machines:
        gaps = rng.geometric(p, max(16, int(1.2 * p * (machines - at)) + 8))
        steps = at + np.cumsum(gaps)
        out.append(steps)
        at = int(steps[-1])
    every = np.concatenate(out)
    return every[every < machines]


def coefficients(k: int, seed: int, rep: int = 0, prime: int = P31) -> list[int]:
    """k coefficients of a polynomial of degree k - 1, fresh for each repetition."""
    rng = random.Random(f"{seed}/{rep}")
    return [rng.randrange(prime) for _ in range(k)]


def kwise(x: Column, coeffs: list[int], prime: int = P31) -> Column:
    """The polynomial's value at x modulo the prime, by Horner; x below the prime (31 bits: BIGINT products)."""
    if prime > 1 << 31:
        x, h = x.cast("decimal(38,0)"), F.lit(coeffs[0]).cast("decimal(38,0)")
        for c in coeffs[1:]:
            h = ((h * x + F.lit(c)) % F.lit(prime)).cast("decimal(19,0)").cast("decimal(38,0)")
        return h.cast("long")
    if len(coeffs) > 16:  # one fold instead of a deep tree of expressions
        return F.aggregate(F.array(*map(F.lit, coeffs)).cast("array<long>"), F.lit(0).cast("long"), lambda h, c: (h * x + c) % prime)
    h = F.lit(coeffs[0]).cast("long")
    for c in coeffs[1:]:
        h = (h * x + F.lit(c)) % F.lit(prime)
    return h


def kwise_sql(x: str, coeffs: list[int], prime: int = P31) -> str:
    """The same in SQL text."""
    h = f"CAST({coeffs[0]} AS BIGINT)"
    for c in coeffs[1:]:
        h = f"(({h} * {x} + {c}) % {prime})"
    return h


def threshold(p: float, prime: int = P31) -> int:
    """Values below it are sampled."""
    return int(p * prime)
