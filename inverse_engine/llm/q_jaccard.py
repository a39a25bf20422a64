"""op9: the component of every document under links of Jaccard similarity 0.9 of 3-word shingles.

SQL could only say it over all pairs; tests/llm checks against brute force."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.signature_trees import jaccard_components


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")
