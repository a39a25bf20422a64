"""The corpus pipeline: quality rules, quality classifier, near-duplicate join, span deduplication, packing.

Each stage takes (spark, docs, sf_dir), works on all rows that it is given, and returns a DataFrame; run() writes each stage's
rows as Parquet and reads them again as the next one's docs. All but the last return the columns of `documents`; the last returns
the pieces of sequences. Empty tables pass through every stage; null texts fail the quality rules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.llm import decision_list, packing, quality_net, sentence_spans, signature_trees
from inverse_engine.llm.common import discard_since, materialise, release, steps, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the learned decision list and the base rule keep. Rules are learned from the labels among docs."""
    rules = decision_list.learn(docs, table(spark, sf_dir, "labels"))
    # A column that is no function of its row, which the condition reads: a condition on `kept` alone would sink to the scan, with every
    # measure inside every lambda. It writes no second copy of the texts.
    judged = decision_list.apply_rules(decision_list.measured(docs, *COLUMNS), rules).select(*COLUMNS, "kept", F.monotonically_increasing_id().alias("row"))
    return judged.where("kept AND row >= 0").select(*COLUMNS)


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose calibrated quality probability is 0.7 or more. What the rules left may hold labels of one kind only:
    then the classifier has nothing to tell apart, and it keeps all."""
    model = quality_net.learn_all(docs, table(spark, sf_dir, "labels"))
    if model is None:
        return docs.select(*COLUMNS)
    scored = quality_net.score(docs, model, *COLUMNS)
    return scored.where(F.col("score") >= 0.7).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the least id, of each group under links of similarity 0.8 of five-word shingles.

    Documents without words stay. Rows are told apart by id and text, so null and repeated ids do no harm; of rows that repeat
    both, one stays, by the order of the other columns."""
    before = steps()
    found = materialise(signature_trees.jaccard_components(docs, n=5, part=80, whole=100).select("doc_id", "place", "node", "component_id", "component_place"), "pipeline-components")
    discard_since(before, found)
    worded = found.where(F.col("node").isNotNull())
    stays = F.col("doc_id").eqNullSafe(F.col("component_id")) & (F.col("place") == F.col("component_place"))
    key = [F.coalesce(F.col("doc_id").cast("long"), F.lit(signature_trees.NO_ID)).alias("id"), "place"]
    gone = worded.where(~stays).select(*key).distinct()
    repeated = worded.where(stays).groupBy(*key).agg(F.count("*").alias("n")).where("n > 1")
    marked = docs.select(*COLUMNS, F.xxhash64("text").alias("place"), F.coalesce(F.col("doc_id").cast("long"), F.lit(signature_trees.NO_ID)).alias("id"))
    kept = marked.join(gone, ["id", "place"], "left_anti")
    if repeated.head(1):
        twice = materialise(repeated.select("id", "place"), "pipeline-repeated")
        again = kept.join(twice, ["id", "place"], "left_semi").groupBy("id", "place").agg(F.min(F.struct(*COLUMNS)).alias("d")).select("d.*")
        kept = kept.join(twice, ["id", "place"], "left_anti").select(*COLUMNS).unionByName(again)
    return kept.select(*COLUMNS)


def span_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without repeated sentence runs; a document of which no word is left goes."""
    cut = sentence_spans.dedup_spans(docs.select(*COLUMNS))
    empty = (F.col("n_removed") > 0) & ~F.col("text").rlike(r"[^\x20\x09-\x0D]")
    return cut.where(~F.coalesce(empty, F.lit(False))).withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents in sequences of at most 2048 ids."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality rules", quality_rules),
    ("quality classifier", quality_classifier),
    ("n-gram Jaccard join", near_duplicates),
    ("substring dedup", span_dedup),
    ("packing", packed),
]
#: Two stages are learned models, which SQL cannot express; tests/llm holds the rest against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    before = steps()
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, f"pipeline-{name.replace(' ', '-')}")
            discard_since(before, docs)  # a stage's own steps go when its result is written
            release(spark)
    return docs
