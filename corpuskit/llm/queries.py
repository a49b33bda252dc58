"""The registered queries of this subpackage: one for each operator, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpuskit.llm import byte_bpe, chat, html_text, maxscore, near_dedup, packing, quality, repetition, token_counts, wavelet
from corpuskit.llm.common import table


def op1_offset_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.attribute_tokens(table(spark, sf_dir, "documents"))


def op2_maxscore_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxscore.neighbours(table(spark, sf_dir, "embeddings"))


def op3_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicate_classes(table(spark, sf_dir, "documents"))


def op4_weak_label_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"))


def op5_forced_boundary_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.round_trip(table(spark, sf_dir, "documents"))


def op6_quotation_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.format_conversations(table(spark, sf_dir, "conversations"))


def op7_repetition_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repetition.digest(table(spark, sf_dir, "documents"))


def op8_wavelet_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wavelet.round_trip(table(spark, sf_dir, "documents"))


def op9_html_block_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract_pages(table(spark, sf_dir, "pages"))


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"))


_ALL = (
    op1_offset_token_counts, op2_maxscore_topk, op3_minhash_near_dedup, op4_weak_label_quality, op5_forced_boundary_bpe,
    op6_quotation_linking, op7_repetition_rules, op8_wavelet_token_files, op9_html_block_rules, op10_best_fit_packing,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in _ALL}


def oracle_sql() -> dict[str, str]:
    """Operators that SQL can express on whole tables; the others are tested against brute force."""
    return {"op2_maxscore_topk": maxscore.oracle()}
