"""Streams give what the batch queries give."""

from pyspark.sql import functions as F

from inverse_engine.operators.common import gathered
from inverse_engine.sources import query_sets
from inverse_engine.sources.points import fixture
from inverse_engine.streaming import profiles

SF = "/root/testdata/sf0.001"


def drain(stream, name, mode):
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination(120)
    return stream.sparkSession.table(name)


def test_profiles_and_repetitions(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartitionByRange(3, "ts").write.parquet(f"{tmp_path}/in")
    live = drain(profiles.user_profiles(profiles.read_events(spark, f"{tmp_path}/in"), "1 day", late="40 days"), "profiles", "complete")
    assert sorted(map(tuple, live.collect())) == sorted(map(tuple, profiles.user_profiles(events, "1 day").collect()))
    events.write.mode("append").parquet(f"{tmp_path}/in")
    once = drain(profiles.once_each(profiles.read_events(spark, f"{tmp_path}/in"), "40 days"), "once", "append")
    assert once.count() == events.count()


def test_continuous_range_query(spark, tmp_path):
    points = fixture(spark, SF, "orders2")
    points.repartition(3).write.parquet(f"{tmp_path}/points")
    rows = gathered(points, query_sets.sample_query_sets(points, 3, 2, 0.01)).withColumn("eps", F.lit(0.1))
    stream = spark.readStream.schema(points.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/points")
    live = drain(profiles.continuous_eps_range(stream, rows, 2), "ranges", "append")
    assert sorted(map(tuple, live.collect())) == sorted(map(tuple, profiles.continuous_eps_range(points, rows, 2).collect()))
