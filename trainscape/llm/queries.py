"""Queries of the corpus operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from trainscape.llm import html_extract, language_id, mixing, near_dedup, quality_rules, secret_scan, sentencepiece_fst, topk_search, toxicity, warc_zip

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_near_dedup": near_dedup.op1_near_dedup,
    "op2_quality_rules": quality_rules.op2_quality_rules,
    "op3_mix_sources": mixing.op3_mix_sources,
    "op4_html_extract": html_extract.op4_html_extract,
    "op5_warc_packages": warc_zip.op5_warc_packages,
    "op6_sentencepiece": sentencepiece_fst.op6_sentencepiece,
    "op7_toxicity": toxicity.op7_toxicity,
    "op8_secret_scan": secret_scan.op8_secret_scan,
    "op9_topk_search": topk_search.op9_topk_search,
    "op10_language_id": language_id.op10_language_id,
}

ORACLES: dict[str, str] = {
    "op2_quality_rules": quality_rules.OP2_SQL,
    "op3_mix_sources": mixing.OP3_SQL,
    "op9_topk_search": topk_search.OP9_SQL,
}
