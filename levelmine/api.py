"""The mining job: a user's filters, mapper and reducer around the exploration."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelmine.balance.predict import dealt
from levelmine.explore import edge, vertex
from levelmine.explore.loop import predicted_rows
from levelmine.explore.vertex import EFilter, Level
from levelmine.graph.model import PropertyGraph
from levelmine.pattern.classify import classify
from levelmine.plans.planner import plan
from levelmine.session import materialise
from levelmine.store.hybrid import Storage

Mapper = Callable[[DataFrame], DataFrame]
Reducer = Callable[[DataFrame], DataFrame]


def count_mapper(level: DataFrame) -> DataFrame:
    """(labels, bits, value): one for each embedding."""
    return level.select("labels", "bits", F.lit(1).cast("long").alias("value"))


def sum_reducer(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("pattern").agg(F.sum("value").alias("value"))


def filtered(patterns: DataFrame, pfilter: Column | Callable[[DataFrame], Column] | None) -> DataFrame:
    if pfilter is None:
        return patterns
    return patterns.filter(pfilter if isinstance(pfilter, Column) else pfilter(patterns))


def aggregate(level: DataFrame, mapper: Mapper = count_mapper, reducer: Reducer = sum_reducer, pfilter=None, labelled: bool = True, engine: str = "exact") -> DataFrame:
    """(pattern, value): mapped pairs are summed by raw form while they are values to add, then the few distinct forms
    are classified, and their values reduced by pattern."""
    if not labelled:
        level = level.withColumn("labels", F.array_repeat(F.lit(1), F.size("labels")))
    pairs = mapper(level)
    if mapper is count_mapper:
        pairs = pairs.groupBy("labels", "bits").agg(F.sum("value").alias("value"))
    codes = classify(pairs.select("labels", "bits").distinct(), engine)
    coded = pairs.join(codes, ["labels", "bits"])  # adaptive execution broadcasts them if they turn out small
    coded = coded.withColumnRenamed("code", "pattern").drop("labels", "bits")
    return filtered(reducer(coded), pfilter)


@dataclass
class MiningJob:
    """loop: 'last' aggregates after the last round, 'each' after every round and keeps the embeddings of the patterns
    that pass. mapper=None: all embeddings have one pattern, so they are only counted. balance: 'even' or 'predicted' deals
    a level out to `parts` tasks by number or by predicted work before it is grown; None leaves that to the scheduler."""

    graph: PropertyGraph
    k: int
    mode: str = "vertex"
    efilter: EFilter = None
    pfilter: Column | Callable[[DataFrame], Column] | None = None
    mapper: Mapper | None = count_mapper
    reducer: Reducer = sum_reducer
    loop: str = "last"
    labelled: bool = True
    engine: str = "exact"
    storage: Storage | None = None
    max_rows: int | None = None
    balance: str | None = None
    parts: int = 8

    def _aggregate(self, level: Level) -> DataFrame:
        return aggregate(level.df, self.mapper, self.reducer, self.pfilter, self.labelled, self.engine)

    def run(self) -> DataFrame:
        """(pattern, value) of the last round; (n) without a mapper."""
        if self.balance not in (None, "even", "predicted"):
            raise ValueError("balance: even, predicted")
        module = vertex if self.mode == "vertex" else edge
        carry = plan(self.graph, self.k).carry
        level, storage = module.init(self.graph, carry=carry), self.storage or Storage("disk")
        while level.k < self.k:
            if self.max_rows is not None and level.carried and (n := predicted_rows(level, self.efilter)) > self.max_rows:
                raise RuntimeError(f"level {level.k + 1} would have {n} rows; max_rows is {self.max_rows}")
            if self.loop == "each" and self.mapper is not None and level.k > 1:
                level = self._pruned(level)
            if self.balance and level.carried:
                level = dealt(level, self.parts, self.balance == "predicted")
            if level.k + 1 == self.k:
                level = module.expand(self.graph, level, self.efilter, last=True)
            else:
                level = storage.keep(self.graph, level, self.efilter)
        if self.mapper is None:
            return level.df.agg(F.count("*").alias("n"))
        return self._aggregate(level)

    def _pruned(self, level: Level) -> Level:
        good = materialise(self._aggregate(level).select("pattern"), "good")
        codes = classify(level.df.select("labels", "bits").distinct(), self.engine)
        forms = codes.join(good, F.col("code") == F.col("pattern"), "left_semi").select("labels", "bits")
        return Level(level.df.join(forms, ["labels", "bits"], "left_semi"), level.k, level.carried)


def combine_rows(level: DataFrame) -> DataFrame:
    """(mapped, partial, final): pairs that the mapper makes, rows that tasks pass on after adding up their own, patterns'
    raw forms in the end. What is shuffled is `partial`."""
    form = ["labels", "bits"]
    tasks = level.select(*form).groupBy(F.spark_partition_id().alias("task"), *form).agg(F.count("*").alias("n"))
    each = tasks.groupBy(*form).agg(F.count("*").alias("tasks"), F.sum("n").alias("n"))
    return each.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("mapped"), F.coalesce(F.sum("tasks"), F.lit(0)).cast("long").alias("partial"), F.count("*").alias("final"))
