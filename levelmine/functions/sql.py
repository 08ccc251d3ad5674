"""Functions for SQL: canonical_ok, pattern_code, pattern_name, and the table functions mine_motifs and decode_level."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from levelmine.pattern.exact import canonical
from levelmine.pattern.names import name_of


def _canonical_ok(path: list[int], masks: list[int]) -> bool:
    """masks: for each position the earlier positions that it is adjacent to."""
    for j in range(1, len(path)):
        if not masks[j] or path[j] <= path[0]:
            return False
        first = (masks[j] & -masks[j]).bit_length() - 1
        if any(u > path[j] for u in path[first + 1 : j]):
            return False
    return True


@F.pandas_udf(T.BooleanType())
def canonical_ok(path: pd.Series, masks: pd.Series) -> pd.Series:
    return pd.Series([_canonical_ok(list(map(int, p)), list(map(int, m))) for p, m in zip(path, masks, strict=True)])


@F.pandas_udf(T.StringType())
def pattern_code(labels: pd.Series, bits: pd.Series) -> pd.Series:
    return pd.Series([canonical(tuple(map(int, lab)), int(b))[0] for lab, b in zip(labels, bits, strict=True)])


@F.pandas_udf(T.StringType())
def pattern_name(code: pd.Series) -> pd.Series:
    return code.map(lambda c: name_of(c) or c)


class MineMotifs:
    """TABLE(src, dst) of one small component a partition -> (motif, frequency): subgraphs of k vertices by shape.

    For many small graphs at once, one a partition key; a large graph is explored by the engine instead.
    """

    @staticmethod
    def analyze(edges: AnalyzeArgument, k: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(T.StructType([T.StructField("motif", T.StringType()), T.StructField("frequency", T.LongType())]))

    def __init__(self):
        self.near, self.k = {}, 3

    def eval(self, row, k: int):
        self.k = k
        if row["src"] != row["dst"]:
            self.near.setdefault(row["src"], set()).add(row["dst"])
            self.near.setdefault(row["dst"], set()).add(row["src"])

    def terminate(self):
        from collections import Counter

        found = {frozenset([v]) for v in self.near}
        for _ in range(self.k - 1):
            found = {s | {w} for s in found for v in s for w in self.near[v] if w not in s}
        counts = Counter()
        for s in found:
            at = sorted(s)
            bits = sum(1 << (j * (j - 1) // 2 + i) for j in range(self.k) for i in range(j) if at[j] in self.near[at[i]])
            counts[canonical((1,) * self.k, bits)[0]] += 1
        for code, n in sorted(counts.items()):
            yield name_of(code) or code, n


class DecodeLevel:
    """TABLE(path) -> (place, vert): the vertices of each embedding one by one."""

    @staticmethod
    def analyze(level: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(T.StructType([T.StructField("place", T.IntegerType()), T.StructField("vert", T.LongType())]))

    def eval(self, row):
        yield from enumerate(row["path"])


def register(spark: SparkSession) -> None:
    for name, f in (("canonical_ok", canonical_ok), ("pattern_code", pattern_code), ("pattern_name", pattern_name)):
        spark.udf.register(name, f)
    spark.udtf.register("mine_motifs", F.udtf(MineMotifs))
    spark.udtf.register("decode_level", F.udtf(DecodeLevel))
