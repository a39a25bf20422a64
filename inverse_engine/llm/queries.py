"""The queries of this subpackage, for the driver's contract: each derives the asked columns from its operator's output."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

#: Query name -> module here with `query(spark, sf_dir)` and, where SQL can say it, `ORACLE_SQL`.
MODULES = {
    "op1_toxicity_grammar": "q_toxicity",
    "op2_exact_inner_product_topk": "q_topk",
    "op3_decision_list_rules": "q_rules",
    "op4_random_indexing_quality": "q_quality",
    "op5_histogram_sort_shards": "q_shards",
    "op6_log_bilinear_scores": "q_language_model",
    "op7_segment_tree_bpe": "q_bpe",
    "op8_sentence_span_dedup": "q_spans",
    "op9_signature_tree_join": "q_jaccard",
    "op10_differencing_packs": "q_packing",
}


def _call(module: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: import_module(f"{__package__}.{module}").query(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: _call(module) for name, module in MODULES.items()}


def oracle_sql() -> dict[str, str]:
    found = {name: getattr(import_module(f"{__package__}.{module}"), "ORACLE_SQL", None) for name, module in MODULES.items()}
    return {name: sql for name, sql in found.items() if sql}
