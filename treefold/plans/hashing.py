"""k-wise independent hashing of vertices to machines, as native column expressions."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1
WIDE_PRIME = (1 << 61) - 1


class PolyHash:
    """A random polynomial of degree k-1 modulo a prime, then modulo m: k-wise independent.

    The coefficients are drawn once on the driver and are literals of the plan,
    so every task evaluates the same function without communication.
    """

    def __init__(self, m: int, k: int | None = None, seed: int = 0):
        self.m = m
        self.k = max(2, k if k is not None else math.ceil(math.log2(max(2, m))))
        rng = np.random.default_rng(seed)
        self.coefficients = [int(rng.integers(0, PRIME)) for _ in range(self.k)]
        if self.coefficients[0] == 0:
            self.coefficients[0] = 1
        self.wide = [c * int(rng.integers(1, 1 << 30)) % WIDE_PRIME for c in self.coefficients]

    def column(self, key: Column) -> Column:
        """For keys below 2^31 - 1: Horner's rule in 64-bit arithmetic, inside code generation."""
        x = F.pmod(key.cast("long"), F.lit(PRIME))
        value = F.lit(self.coefficients[0]).cast("long")
        for c in self.coefficients[1:]:
            value = F.pmod(value * x + F.lit(c), F.lit(PRIME))
        return F.pmod(value, F.lit(self.m)).cast("int")

    def wide_column(self, key: Column) -> Column:
        """For any 64-bit key: the same modulo 2^61 - 1 in decimal arithmetic."""
        p = F.lit(WIDE_PRIME).cast("decimal(20,0)")
        x = F.pmod(key.cast("decimal(20,0)"), p).cast("decimal(19,0)")
        value = F.lit(self.wide[0]).cast("decimal(19,0)")
        for c in self.wide[1:]:
            value = F.pmod((value * x).cast("decimal(38,0)") + F.lit(c).cast("decimal(19,0)"), p).cast("decimal(19,0)")
        return F.pmod(value, F.lit(self.m)).cast("int")

    def sql(self, key: str, wide: bool = False) -> str:
        """The same function as SQL over 128-bit integers."""
        prime, coefficients = (WIDE_PRIME, self.wide) if wide else (PRIME, self.coefficients)
        x = f"(cast({key} AS HUGEINT) % {prime})"
        value = f"cast({coefficients[0]} AS HUGEINT)"
        for c in coefficients[1:]:
            value = f"(({value} * {x} + {c}) % {prime})"
        return f"cast({value} % {self.m} AS BIGINT)"

    def evaluate(self, keys: np.ndarray) -> np.ndarray:
        x = np.asarray(keys, np.uint64) % np.uint64(PRIME)
        value = np.full(x.shape, self.coefficients[0], np.uint64)
        for c in self.coefficients[1:]:
            value = (value * x + np.uint64(c)) % np.uint64(PRIME)
        return (value % np.uint64(self.m)).astype(np.int64)


PLACEMENTS = ("hash", "narrow", "spark")


def distribute(tree: DataFrame, h: PolyHash, key: str = "node_id", placement: str = "hash") -> DataFrame:
    """Adds the machine of each row, and puts each machine's rows into its own partition.

    'hash' takes any 64-bit key; 'narrow' is cheaper, for keys below 2^31 - 1 only.
    'spark' leaves the exchange to Spark's own hash, which later joins on the key can reuse.
    """
    if placement not in PLACEMENTS:
        raise ValueError(f"placement must be one of {PLACEMENTS}")
    marked = tree.withColumn("machine", h.column(F.col(key)) if placement == "narrow" else h.wide_column(F.col(key)))
    if placement == "spark":
        return marked.repartition(h.m, key)
    return marked.repartitionById(h.m, "machine")


def is_distributable(df: DataFrame, weight: str, n: int, m: int, total_factor: float = 4.0) -> bool:
    """Total weight O(n) and largest weight at most n/m up to a log factor."""
    row = df.agg(F.coalesce(F.sum(weight), F.lit(0)), F.coalesce(F.max(weight), F.lit(0))).first()
    return row[0] <= total_factor * n and row[1] <= n / m * max(1.0, math.log2(max(2, n)))
