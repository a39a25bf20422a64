"""Connected components of links in a DataFrame, by contraction towards the smallest node."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import materialise


def components(links: DataFrame, name: str, most_rounds: int = 60) -> DataFrame:
    """(node, label) for every node of `links` (a, b: long): label is the smallest node that it reaches.

    Each round points every node, and its other parents, at its least parent, then at that one's parent. Sums before the
    exchange keep hubs from becoming hot, and the pointer join has an exchange on both sides, so a hub's rows can be split."""
    up = links.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("x"), F.least("a", "b").alias("p")).distinct()
    up = materialise(up, f"{name}-links")
    for _ in range(most_rounds):
        least = materialise(up.groupBy("x").agg(F.min("p").alias("m"), F.max("p").alias("o")), f"{name}-least")
        many = least.where(F.col("m") != F.col("o"))
        others = up.join(many, "x").where(F.col("p") != F.col("m")).select(F.col("p").alias("x"), F.col("m").alias("p"))
        stars = least.select("x", F.col("m").alias("p"))
        jump = stars.alias("s").join(least.select(F.col("x").alias("y"), F.col("m").alias("q")).alias("l"), F.col("p") == F.col("y"), "left")
        moved = jump.select("x", F.coalesce("q", "p").alias("p"), F.col("q").isNotNull().alias("moved"))
        new = materialise(moved.unionByName(others.withColumn("moved", F.lit(True))), f"{name}-moved")
        if not new.where("moved").head(1):
            return new.select(F.col("x").alias("node"), F.col("p").alias("label")).unionByName(new.select(F.col("p").alias("node"), F.col("p").alias("label")).distinct())
        up = new.select("x", "p").distinct()
    raise RuntimeError(f"no end after {most_rounds} rounds; a chain of links is longer than 2**{most_rounds}")
