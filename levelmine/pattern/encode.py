"""Raw patterns: labels by position and the bits of the upper triangle. Many raw forms are one pattern."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

K_MAX = 8


def check_size(k: int, engine: str = "exact") -> None:
    if k > K_MAX:
        raise ValueError(f"the {engine} engine takes at most {K_MAX} vertices, not {k}")


def bit(i: int, j: int) -> int:
    i, j = min(i, j), max(i, j)
    return j * (j - 1) // 2 + i


def matrix(k: int, bits: int) -> list[list[int]]:
    m = [[0] * k for _ in range(k)]
    for j in range(k):
        for i in range(j):
            m[i][j] = m[j][i] = bits >> bit(i, j) & 1
    return m


def bits_of(k: int, edges) -> int:
    out = 0
    for i, j in edges:
        out |= 1 << bit(i, j)
    return out


def raw_counts(level: DataFrame, labelled: bool = True) -> DataFrame:
    """(labels, bits, n): the level by raw pattern; without labels all are 1."""
    key = ["labels", "bits"]
    if not labelled:
        level = level.withColumn("labels", F.array_repeat(F.lit(1), F.size("labels")))
    return level.groupBy(*key).agg(F.count("*").alias("n"))
