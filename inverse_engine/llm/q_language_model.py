"""op6: add-one unigram and log-bilinear log10 probabilities of every document. tests/llm checks the counts and the normalisation."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.language_model import language_model_scores


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_model_scores(table(spark, sf_dir, "documents"))
