"""op10: all documents into sequences of at most 2048 ids. tests/llm checks ids, coverage and capacity."""

from pyspark.sql import DataFrame, SparkSession

from inverse_engine.llm.common import table
from inverse_engine.llm.packing import pack


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
