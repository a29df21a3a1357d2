"""The dealt operators' queries and, where SQL expresses them, their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from lexbridge import reach
from lexbridge.llm import line_dedup, mixing
from lexbridge.llm.decontaminate import find_leaks
from lexbridge.llm.embedding_dedup import near_duplicate_vectors
from lexbridge.llm.jaccard_join import link_components
from lexbridge.llm.language_id import language_report
from lexbridge.llm.line_dedup import dedup_lines
from lexbridge.llm.mixing import mix_sources
from lexbridge.llm.passage_dedup import repeated_passages
from lexbridge.llm.pii import find_pii
from lexbridge.llm.toxicity import toxicity_report
from lexbridge.llm.url_filter import judge_urls


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reach(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_report(_table(spark, sf_dir, "documents"))


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(_table(spark, sf_dir, "documents").select("doc_id", "text", "source"))


def op3_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_components(_table(spark, sf_dir, "documents"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_passages(_table(spark, sf_dir, "documents"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_report(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_pii(_table(spark, sf_dir, "documents"))


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op8_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(_table(spark, sf_dir, "embeddings"))


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(_table(spark, sf_dir, "pages"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_language_id": op1_language_id,
    "op2_mix_sources": op2_mix_sources,
    "op3_ngram_jaccard_join": op3_ngram_jaccard_join,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_toxicity": op5_toxicity,
    "op6_pii": op6_pii,
    "op7_decontaminate": op7_decontaminate,
    "op8_embedding_dedup": op8_embedding_dedup,
    "op9_url_filter": op9_url_filter,
    "op10_line_dedup": op10_line_dedup,
}
ORACLES: dict[str, str] = {
    "op2_mix_sources": mixing.ORACLE,
    "op10_line_dedup": line_dedup.ORACLE,
}
