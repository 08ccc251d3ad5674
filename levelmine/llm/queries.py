"""The operators' queries: each over its whole table, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.llm import decontaminate, quality, warc
from levelmine.llm.bpe import encode_digests
from levelmine.llm.crosspolytope import nearest
from levelmine.llm.lm import stupid_backoff
from levelmine.llm.order import training_order
from levelmine.llm.repeats import difference_cover, remove_repeats, sparse_suffixes
from levelmine.llm.simhash import near_duplicates
from levelmine.session import read_table


def op1_cross_polytope_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(read_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).drop("text_key")


def op4_bpe_encode_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_digests(read_table(spark, sf_dir, "documents"))


def op5_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return training_order(read_table(spark, sf_dir, "documents"))


def op6_stupid_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document is scored by the others: its own counts would make every n-gram of it a seen one."""
    return stupid_backoff(read_table(spark, sf_dir, "documents"), leave_out=True)


def op7_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of 50 words or more that occurs more than once; all but its first occurrence go."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    out = remove_repeats(docs, sparse_suffixes(50))
    return out.filter("r_repeated > 0").select("doc_id", F.col("r_words").alias("n_words"), F.col("r_repeated").alias("n_repeated"), F.col("r_removed").alias("n_removed"), F.col("r_sha").alias("kept_sha256"))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality.fit(docs, read_table(spark, sf_dir, "labels"))
    scored = quality.score(docs, model)
    return scored.select("doc_id", quality.held_out().alias("held_out"), F.col("r_score").alias("score"), F.col("r_predicted").alias("predicted"))


def op9_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(read_table(spark, sf_dir, "pages"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    out = remove_repeats(docs, difference_cover(20))
    return out.select("doc_id", F.col("r_words").alias("n_words"), F.col("r_removed").alias("n_removed"), F.col("r_sha").alias("kept_sha256"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_cross_polytope_search, op2_simhash_near_dedup, op3_benchmark_decontamination, op4_bpe_encode_decode, op5_training_order, op6_stupid_backoff, op7_suffix_array_dedup, op8_quality_classifier, op9_warc_round_trip, op10_substring_dedup)}


def oracle_sql() -> dict[str, str]:
    return {"op3_benchmark_decontamination": decontaminate.ORACLE}
