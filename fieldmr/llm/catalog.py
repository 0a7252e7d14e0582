"""Queries of the training-data operators, and SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import oracles
from .decontam import contamination, digest
from .htmltext import page_text
from .langid import identify_languages
from .linefreq import line_frequency
from .mixing import mix_rates
from .neardup import near_duplicates
from .runtime import read_table
from .suffixdedup import repeated_spans
from .tokencount import count_tokens
from .tokenfile import token_table
from .toxicity import rate_toxicity

Query = Callable[[SparkSession, str], DataFrame]


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(contamination(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")))


def op2_line_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_frequency(read_table(spark, sf_dir, "documents")).drop("text")


def op3_rans_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_table(read_table(spark, sf_dir, "documents"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify_languages(read_table(spark, sf_dir, "documents"))


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_rates(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(read_table(spark, sf_dir, "documents"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rate_toxicity(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_text(read_table(spark, sf_dir, "pages"))


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_spans(read_table(spark, sf_dir, "documents")).drop("spans")


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpus_pipeline import run

    return run(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {q.__name__: q for q in (op1_decontamination, op2_line_frequency, op3_rans_tokens, op4_language, op5_mixing, op6_token_counts, op7_toxicity, op8_html_text, op9_suffix_dedup, op10_near_duplicates, pipeline)}


def oracle_sql() -> dict[str, str]:
    return {"op1_decontamination": oracles.DECONTAMINATION, "op2_line_frequency": oracles.LINE_FREQUENCY,
        "op9_suffix_dedup": oracles.REPEATED_SPANS, "op10_near_duplicates": oracles.NEAR_DUPLICATES}
