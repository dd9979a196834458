"""Queries of the training-data operators, and the DuckDB SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, language, quality, sharding, topk, toxicity, unigram, warc, wrappers
from .common import table
from .setsketch import near_duplicates


def op9_setsketch_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op6_columnar_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.exact_top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5)


def op8_unigram_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unigram.encode(table(spark, sf_dir, "documents"))


def op10_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    captures = warc.archive_round_trip(table(spark, sf_dir, "pages"))
    return captures.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "key", "file", "offset", "length")


def op4_balanced_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.balanced_shards(table(spark, sf_dir, "documents"), shards=40)


def op5_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.verdicts(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_rule_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_boosted_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op1_host_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wrappers.extract(table(spark, sf_dir, "pages"))


def op3_kneser_ney_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.predict(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_host_wrappers": op1_host_wrappers,
    "op2_rule_quality": op2_rule_quality,
    "op3_kneser_ney_language": op3_kneser_ney_language,
    "op4_balanced_shards": op4_balanced_shards,
    "op5_template_decontamination": op5_template_decontamination,
    "op6_columnar_topk": op6_columnar_topk,
    "op7_boosted_toxicity": op7_boosted_toxicity,
    "op8_unigram_pieces": op8_unigram_pieces,
    "op9_setsketch_neardup": op9_setsketch_neardup,
    "op10_warc_index": op10_warc_index,
}

ORACLE_SQL: dict[str, str] = {
    "op6_columnar_topk": topk.ORACLE,
}
