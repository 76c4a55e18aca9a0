"""The queries of this subpackage and their SQL; __spark_entry__.py adds them when it can be imported."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from seqgrid.llm import chat, decontam, html_template, jaccard, language, lm_score, media, packing, quality, sharding

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_packing": packing.op1_packing,
    "op2_language_id": language.op2_language_id,
    "op3_benchmark_decontamination": decontam.op3_benchmark_decontamination,
    "op4_lm_scoring": lm_score.op4_lm_scoring,
    "op5_chat_formatting": chat.op5_chat_formatting,
    "op6_ngram_jaccard_join": jaccard.op6_ngram_jaccard_join,
    "op7_html_extraction": html_template.op7_html_extraction,
    "op8_media_clips": media.op8_media_clips,
    "op9_quality_classifier": quality.op9_quality_classifier,
    "op10_sharding": sharding.op10_sharding,
    "sharding_small": sharding.sharding_small,
}
ORACLES: dict[str, str] = {"op5_chat_formatting": chat.ORACLE, "op10_sharding": sharding.oracle(sharding.LIMIT), "sharding_small": sharding.oracle(64 << 10)}
