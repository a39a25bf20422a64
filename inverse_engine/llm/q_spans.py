"""op8: every document without its repeated sentence runs. tests/llm checks against a brute-force version."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.sentence_spans import dedup_spans


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_spans(table(spark, sf_dir, "documents").select("doc_id", "text"))
