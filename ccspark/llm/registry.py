"""Queries of the pipeline operators over whole tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ccspark.llm import byte_bpe, chat, decontaminate, line_dedup, ppm, quality, secrets, simhash, substrings, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_line_dedup(spark, sf_dir):
    return line_dedup.dedup(_table(spark, sf_dir, "documents"), digest=True)


def op2_url_filter(spark, sf_dir):
    return url_filter.judge(_table(spark, sf_dir, "pages"))


def op3_decontaminate(spark, sf_dir):
    return decontaminate.leaks(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op4_quality_rules(spark, sf_dir):
    return quality.judge(_table(spark, sf_dir, "documents"))


def op5_ppm_score(spark, sf_dir):
    return ppm.score_corpus(_table(spark, sf_dir, "documents"))


def op6_substring_dedup(spark, sf_dir):
    return substrings.remove(_table(spark, sf_dir, "documents"), digest=True)


def op7_byte_bpe(spark, sf_dir):
    import public_tokenizers

    return byte_bpe.encode_digests(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op8_chat_format(spark, sf_dir):
    return chat.format_chats(_table(spark, sf_dir, "conversations"))


def op9_secret_scan(spark, sf_dir):
    return secrets.scan(_table(spark, sf_dir, "documents"))


def op10_simhash(spark, sf_dir):
    found = simhash.components(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.hex_fingerprint(F.col("fp")).alias("fingerprint"), "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_line_dedup, op2_url_filter, op3_decontaminate, op4_quality_rules, op5_ppm_score, op6_substring_dedup, op7_byte_bpe, op8_chat_format, op9_secret_scan, op10_simhash)}


def oracle_sql() -> dict[str, str]:
    return {
        "op1_line_dedup": line_dedup.ORACLE_SQL,
        "op2_url_filter": url_filter.oracle_sql(),
        "op4_quality_rules": quality.oracle_sql(),
        "op8_chat_format": chat.ORACLE_SQL,
    }
