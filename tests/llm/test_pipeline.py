"""The pipeline's stages on a small table: decisions take effect, columns stay, whole texts are packed."""

import zlib

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from inverse_engine.llm import packing, quality_net
from inverse_engine.llm.common import labelled_by_class, materialise, table

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality rules", "quality classifier", "n-gram Jaccard join", "substring dedup", "packing"]
    docs = table(spark, SF, "documents")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = materialise(stage(spark, docs, SF), "test-stage")
        assert docs.columns == columns and 0 < docs.count() <= before, name
        before = docs.count()
    assert docs.select("doc_id").distinct().count() == docs.count()
    packed = corpus_pipeline.packed(spark, docs, SF).toPandas()
    assert set(packed["doc_id"]) == {r["doc_id"] for r in docs.select("doc_id").collect()}
    assert packed.groupby("sequence_id")["length"].sum().max() <= packing.CAPACITY


def test_near_duplicates_with_null_and_repeated_ids(spark):
    words = [f"w{i}" for i in range(80)]
    a, b, other = " ".join(words), " ".join([*words[:-1], "end"]), "another text that is its own one here"
    rows = [(None, a), (4, b), (4, b), (7, a), (9, other), (9, "a text of its own under the same id"), (None, None), (12, None), (None, other + " x y"), (None, other + " x y")]
    docs = spark.createDataFrame([(d, t, "en", "s", 1) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long").withColumn("place", F.lit(1))
    got = [(r["doc_id"], r["text"]) for r in corpus_pipeline.near_duplicates(spark, docs.drop("place"), SF).collect()]
    assert sorted(got, key=str) == sorted([(4, b), (9, other), (9, "a text of its own under the same id"), (None, None), (12, None), (None, other + " x y")], key=str)


def test_empty_table(spark):
    docs = table(spark, SF, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = materialise(stage(spark, docs, SF), "test-empty")
    assert docs.count() == 0


def test_classifier_uses_rare_labels_of_every_fold(spark, tmp_path):
    docs = table(spark, SF, "documents").where("doc_id is not null")
    ids = sorted(r["doc_id"] for r in docs.select("doc_id").distinct().collect())
    bad = [d for d in ids if zlib.crc32(str(d).encode()) % 4 == 2][:2]
    spark.createDataFrame([(d, int(d not in bad), 0) for d in ids], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    kept = {r["doc_id"] for r in corpus_pipeline.quality_classifier(spark, docs, str(tmp_path)).select("doc_id").collect()}
    assert len(kept) >= 0.9 * len(ids)
    one = tmp_path / "one"
    spark.createDataFrame([(d, 1, 0) for d in ids] + [(-1, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(str(one / "labels.parquet"))
    assert corpus_pipeline.quality_classifier(spark, docs, str(one)).count() == docs.count()


def test_rare_labels_are_not_thinned(spark):
    labels = spark.range(5000).selectExpr("id as doc_id", "cast(id % 1000 != 0 as int) as quality")
    sample, shares = labelled_by_class(labels, "quality", 400)
    counts = {r["y"]: r["count"] for r in sample.groupBy("y").count().collect()}
    assert counts[0] == 5 and shares[0] == 1 and 100 <= counts[1] <= 300
    for y in (np.array([1.0] * 40 + [0.0]), np.array([0.0, 1, 1, 1, 1])):
        order, held = quality_net.fifths_by_class(y)
        assert sorted(order) == list(range(len(y))) and set(y[order][: len(y) - held]) == {0.0, 1.0}


def test_shuffle_files_of_written_steps_go(spark):
    import os
    import time

    from inverse_engine.llm.common import materialise, release

    def held():
        manager = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
        return {n for d in manager.localDirsString() for _, _, names in os.walk(d) for n in names if n.startswith("shuffle_")}

    before = held()
    materialise(spark.range(20000).repartition(7).groupBy("id").count(), "released")
    release(spark)
    for _ in range(50):
        if not held() - before:
            break
        time.sleep(0.2)
    assert not held() - before


def test_stages_leave_no_copies_of_texts_or_sets(spark):
    from inverse_engine.llm import decision_list
    from inverse_engine.llm.common import steps

    docs, before = table(spark, SF, "documents"), steps()
    kept = corpus_pipeline.quality_rules(spark, docs, SF)
    rules = decision_list.learn(docs, table(spark, SF, "labels"))
    plain = materialise(decision_list.apply_rules(decision_list.measured(docs, "doc_id", "text"), rules).select("doc_id", "text", "kept"), "test-judged")
    wanted = plain.where("kept").select("doc_id", "text")
    assert kept.count() > 0 and kept.select("doc_id", "text").exceptAll(wanted).count() == 0 == wanted.exceptAll(kept.select("doc_id", "text")).count()
    left = {p for p in steps() - before if "test-judged" not in p}
    corpus_pipeline.near_duplicates(spark, docs, SF)
    for path in {p for p in steps() - before if "test-judged" not in p}:
        assert not {"text", "members", "cells"} & set(spark.read.parquet(path).columns), path
    assert len(steps() - before - left) <= 3
