"""The queries of the training-data operators: name, function and SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..plans.planning import spread
from . import chat_format, html_text, media, mixing, piece_sampling, quality_model, quality_rules, simhash, token_counts, url_filters
from .common import table

Query = Callable[[SparkSession, str], DataFrame]


def tokenizer_path(name: str) -> str:
    """Where the public vocabulary files lie; the path is a parameter of every operator that needs one."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.digest(spread(table(spark, sf_dir, "documents")))


def rule_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.ablation_report(spread(table(spark, sf_dir, "documents")))


def piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_sampling.encode_pieces(spread(table(spark, sf_dir, "documents")), tokenizer_path("piece_bpe_32k.model"))


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filters.filter_urls(table(spark, sf_dir, "pages"))


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(spread(table(spark, sf_dir, "pages")))


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.store_texts(spread(table(spark, sf_dir, "documents")), keep_media=False)


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(spread(table(spark, sf_dir, "documents")), tokenizer_path("byte_bpe_50k.json"))


def op5_piece_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_sampling.sample_pieces(spread(table(spark, sf_dir, "documents")), tokenizer_path("piece_bpe_32k.model"))


def op6_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_model.digest(spread(table(spark, sf_dir, "documents")), table(spark, sf_dir, "labels"))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format.digest(table(spark, sf_dir, "conversations"))


def op9_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.digest(spread(table(spark, sf_dir, "documents")))


def op10_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.account(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_url_filters, op2_html_extraction, op3_media_columns, op4_token_counts, op5_piece_sampling, op6_quality_model, op7_quality_rules, op8_chat_format, op9_simhash_dedup, op10_source_mixing, rule_ablation, piece_encoding)}


def oracle_sql() -> dict[str, str]:
    return {"op1_url_filters": url_filters.ORACLE, "op7_quality_rules": quality_rules.ORACLE, "rule_ablation": quality_rules.ABLATION_ORACLE}
