"""The corpus pipeline: each stage takes the documents that its predecessor kept.

Null texts and ids, empty tables and further columns: as the operators of levelmine.llm define them. doc_id and
text are the key of documents: rows that share a doc_id, or have none, stay apart unless their texts are near copies.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.llm import bpe, decontaminate, jaccard, quality, repeats
from levelmine.session import materialise, read_table


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
_USED = ("doc_id", "text", "n_chars")


def _own_names(stage: Stage) -> Stage:
    """Columns that no stage uses go through under names that clash with none of the operators'."""

    @wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        inner = [c if c in _USED else f"p_{i}" for i, c in enumerate(docs.columns)]
        return stage(spark, docs.toDF(*inner), sf_dir).select(*inner).toDF(*docs.columns)

    return run


@_own_names
def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier does not reject."""
    model = quality.fit(docs, read_table(spark, sf_dir, "labels"))
    return quality.score(docs, model).filter("r_predicted = 1").select(*docs.columns)


@_own_names
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (similarity of five-word sets of 0.8 and more, linked) the document with the least
    doc_id, and of rows that share it there one."""
    named = jaccard.near_copies(docs).groupBy("component", "doc_id", "key").agg(F.count("*").alias("copies"))
    first = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "key", "copies")).alias("s")
    kept = named.groupBy("component").agg(first).select(F.col("s.doc_id").alias("kept_id"), F.col("s.key").alias("kept_key"), F.col("s.copies").alias("copies"))
    kept = materialise(kept, "kept")
    same = F.col("doc_id").eqNullSafe(F.col("kept_id")) & (decontaminate.text_key() == F.col("kept_key"))
    once = docs.join(kept.filter("copies = 1"), same, "left_semi")
    again = kept.filter("copies > 1")
    if again.isEmpty():
        return once
    return once.unionByName(docs.withColumn("c_key", decontaminate.text_key()).join(again, same, "left_semi").dropDuplicates(["doc_id", "c_key"]).drop("c_key"))


@_own_names
def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 words or more are left at their first place only; documents of which nothing is left go."""
    cut = repeats.remove_repeats(docs, repeats.sparse_suffixes(50), with_text=True).filter("r_removed = 0 or r_removed < r_words")
    text = F.when(F.col("r_removed") > 0, F.col("r_text")).otherwise(F.col("text"))
    fresh = {"text": text, "n_chars": F.when(F.col("r_removed") > 0, F.char_length("r_text").cast("long")).otherwise(F.col("n_chars"))}
    return cut.select(*[fresh[c].alias(c) if c in fresh else F.col(c) for c in docs.columns])


@_own_names
def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any window of a benchmark item."""
    hits = decontaminate.contaminated(docs, read_table(spark, sf_dir, "benchmark"))
    same = F.col("doc_id").eqNullSafe(F.col("k_doc")) & (decontaminate.text_key() == F.col("k_text"))
    return docs.join(hits, same, "left_anti")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids and of the decoded text."""
    return bpe.encode_digests(docs)


STAGES = [
    ("quality classifier", keep_good),
    ("SimHash near-dedup", drop_near_copies),
    ("suffix-array dedup", cut_repeats),
    ("benchmark decontamination", drop_contaminated),
    ("BPE encoding and decoding", encode),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.split()[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
