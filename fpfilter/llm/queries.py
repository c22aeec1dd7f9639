"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fpfilter.llm import archives, exact_dedup, language, media, mixing, near_dedup, packing, secrets, substring_dedup, toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_secrets": secrets.op1_secrets,
        "op2_mix_sources": mixing.op2_mix_sources,
        "op3_toxicity": toxicity.op3_toxicity,
        "op4_language": language.op4_language,
        "op5_near_dedup": near_dedup.op5_near_dedup,
        "op6_substring_dedup": substring_dedup.op6_substring_dedup,
        "op7_media": media.op7_media,
        "media_page_sequences": media.page_sequences,
        "op8_warc": archives.op8_warc,
        "op9_packing": packing.op9_packing,
        "op10_exact_dedup": exact_dedup.op10_exact_dedup,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_secrets": secrets.sql(),
        "op2_mix_sources": mixing.SQL,
        "op5_near_dedup": near_dedup.SQL,
        "op8_warc": archives.SQL,
        "op10_exact_dedup": exact_dedup.SQL,
    }
