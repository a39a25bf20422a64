"""op5: all documents into shards 0 to 23 under the law `bytes`. Splitters come from iterated counts, so SQL has no form of it."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.histogram_shards import histogram_shards


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return histogram_shards(table(spark, sf_dir, "documents"), shards=24)
