"""Queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from residual_marginals.llm import best_fit_packing, html_text, label_sharding, pii_semicrf, pu_quality, simhash_gray, suffix_dedup, template_leaks, topk_histogram, warc_index

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_pu_quality": pu_quality.op1_pu_quality,
    "op2_warc": warc_index.op2_warc,
    "op3_pii": pii_semicrf.op3_pii,
    "op4_simhash_groups": simhash_gray.op4_simhash_groups,
    "op5_html_text": html_text.op5_html_text,
    "op6_top_k": topk_histogram.op6_top_k,
    "op7_suffix_dedup": suffix_dedup.op7_suffix_dedup,
    "op8_best_fit": best_fit_packing.op8_best_fit,
    "op9_label_shards": label_sharding.op9_label_shards,
    "op10_template_leaks": template_leaks.op10_template_leaks,
}

SQL: dict[str, str] = {
    "op2_warc": warc_index.OP2_SQL,
    "op5_html_text": html_text.OP5_SQL,
    "op6_top_k": topk_histogram.OP6_SQL,
}
