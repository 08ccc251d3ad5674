"""Figures about runs: ratios, geometric means, agreement of partitions, and the complexity formulas beside them."""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Hashable, Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def geometric_mean(values: Iterable[float]) -> float:
    logs = [math.log(v) for v in values]
    return math.exp(sum(logs) / len(logs))


def speed_up(ours: Iterable[float], theirs: Iterable[float]) -> float:
    """Geometric mean of the ratios of run times."""
    return geometric_mean(t / o for o, t in zip(ours, theirs, strict=True))


def reduction(ours: float, theirs: float) -> float:
    return theirs / ours


def skew(work: Iterable[float]) -> float:
    """Largest over mean."""
    w = list(work)
    return max(w) / (sum(w) / len(w))


def partition_agreement(truth: dict[Hashable, Hashable], keys: dict[Hashable, Hashable]) -> tuple[int, int]:
    """(false merges, false splits): keys that hold several true classes, true classes that several keys hold."""
    held, split = defaultdict(set), defaultdict(set)
    for item, t in truth.items():
        held[keys[item]].add(t)
        split[t].add(keys[item])
    return sum(len(x) - 1 for x in held.values()), sum(len(x) - 1 for x in split.values())


def space_formula(n_vertices: int, n_edges: int, k: int) -> float:
    """Expected rows of a level: E^(k-1) / V^(k-2)."""
    return n_edges ** (k - 1) / n_vertices ** (k - 2)


def time_formula(n_vertices: int, avg_degree: float, k: int) -> float:
    """Embeddings reached: V * d^(k-1)."""
    return n_vertices * avg_degree ** (k - 1)


def speed_ups(runs: DataFrame) -> DataFrame:
    """runs(task, ours, theirs) -> (task, speed_up): geometric means by task, for runs that both ended."""
    ok = runs.filter("ours > 0 and theirs > 0")
    return ok.groupBy("task").agg(F.round(F.exp(F.avg(F.log(F.col("theirs") / F.col("ours")))), 6).alias("speed_up"))
