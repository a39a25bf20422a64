"""op4: a calibrated quality probability for every document. Held-out accuracy is measured in tests/llm."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.llm.common import fold, table
from inverse_engine.llm.quality_net import learn, score


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("doc_id", F.col("doc_id").cast("long"))
    scored = score(docs, learn(docs, table(spark, sf_dir, "labels")), "doc_id")
    return scored.select("doc_id", (fold("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
