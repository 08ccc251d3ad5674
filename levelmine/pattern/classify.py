"""Classes of raw patterns by one of four engines, always over the few distinct raw forms.

exact: the canonical form, the default. spectral: the invariant key. verified: the key of a bucket with one raw form, the
exact form where a bucket holds several; its codes are classes of one call, to be compared within it. search_tree: the
baseline's labelling.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelmine.pattern import exact, search_tree, spectral
from levelmine.pattern.encode import raw_counts
from levelmine.session import materialise

ENGINES = ("verified", "exact", "spectral", "search_tree")


def _coded(engine: str):
    def code(labels: tuple[int, ...], bits: int) -> str:
        if engine == "spectral":
            return spectral.key_text(spectral.key(labels, bits))
        if engine == "search_tree":
            return search_tree.canonical(labels, bits)
        return exact.canonical(labels, bits)[0]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            b["code"] = [code(tuple(int(x) for x in lab), int(bits)) for lab, bits in zip(b["labels"], b["bits"], strict=True)]
            yield b

    return run


def classify(raw: DataFrame, engine: str = "exact") -> DataFrame:
    """raw(labels, bits, ...): adds code."""
    if engine not in ENGINES:
        raise ValueError(f"engines: {', '.join(ENGINES)}")
    if engine != "verified":
        return raw.mapInPandas(_coded(engine), f"{_ddl(raw)}, code string")
    keyed = materialise(raw.mapInPandas(_coded("spectral"), f"{_ddl(raw)}, code string").withColumnRenamed("code", "bucket"), "buckets")
    forms = keyed.groupBy("bucket").agg(F.countDistinct("labels", "bits").alias("forms"))
    both = keyed.join(forms, "bucket")
    many = both.filter("forms > 1").select(*raw.columns).mapInPandas(_coded("exact"), f"{_ddl(raw)}, code string")
    return many.unionByName(both.filter("forms = 1").select(*raw.columns, F.concat(F.lit("key:"), "bucket").alias("code")))


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def positions(raw: DataFrame) -> DataFrame:
    """raw(labels, bits[, elabels]): adds code, place and orbit of each position."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            edges = b["elabels"] if "elabels" in b else [()] * len(b)
            got = [exact.canonical(tuple(int(x) for x in lab), int(bits), tuple((int(e["b"]), int(e["l"])) for e in el)) for lab, bits, el in zip(b["labels"], b["bits"], edges, strict=True)]
            b["code"], b["place"], b["orbit"] = [g[0] for g in got], [list(g[1]) for g in got], [list(g[2]) for g in got]
            yield b

    kept = [c for c in raw.columns if c != "elabels"]
    if "elabels" in raw.columns:  # structs come back as they went only if they are not touched: they are joined by text
        raw = raw.withColumn("form", F.to_json("elabels"))

        def run_text(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in run(batches):
                yield b.drop(columns="elabels")

        ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in raw.schema.fields if f.name in kept)
        return raw.mapInPandas(run_text, f"{ddl}, form string, code string, place array<int>, orbit array<int>")
    return raw.mapInPandas(run, f"{_ddl(raw)}, code string, place array<int>, orbit array<int>")


def pattern_counts(level: DataFrame, labelled: bool = True, engine: str = "exact") -> DataFrame:
    """(code, frequency): raw forms are counted first, the distinct ones classified, and their counts added up."""
    return classify(raw_counts(level, labelled), engine).groupBy("code").agg(F.sum("n").cast("long").alias("frequency"))


def counts_by_embedding(level: DataFrame, labelled: bool = True, engine: str = "spectral") -> DataFrame:
    """(code, frequency) with every single embedding classified: what the two-level counting saves, for comparison."""
    rows = level.select("labels", "bits")
    if not labelled:
        rows = rows.withColumn("labels", F.array_repeat(F.lit(1), F.size("labels")))
    return classify(rows, engine).groupBy("code").agg(F.count("*").alias("frequency"))
