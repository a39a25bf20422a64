"""op3: counts, base rule and the learned decision list's verdict for each document. The list is learned, so SQL has no form of `kept`."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.decision_list import apply_rules, learn, measured


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    rules = learn(docs, table(spark, sf_dir, "labels"))
    return apply_rules(measured(docs, "doc_id"), rules).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")
