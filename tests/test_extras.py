"""The generator source, the table functions and the filter reports."""

from inverse_engine.functions import table_functions
from inverse_engine.operators.framework import DynamicSkyline, EpsRange, Nearest
from inverse_engine.plans.reports import explain_filters
from inverse_engine.sources import query_sets
from inverse_engine.sources.generator import SyntheticPoints
from inverse_engine.sources.points import fixture, lattice, synthetic


def test_generators(spark):
    spark.dataSource.register(SyntheticPoints)
    rows = spark.read.format("synthetic_points").option("rows", "500").option("d", "2").option("clusters", "3").load().collect()
    assert len(rows) == 500 and {r["id"] for r in rows} == set(range(500)) and all(0 <= r["x1"] <= 1 for r in rows)
    assert synthetic(spark, 100, 3, clusters=4).count() == 100
    corners = {(r["x0"], r["x1"]) for r in lattice(spark, 2, 3).collect()}
    assert len(corners) == 9 and (1.0, 0.5) in corners


def test_table_functions(spark):
    table_functions.register(spark)
    assert {r["cell"] for r in spark.sql("SELECT * FROM cells_in_box(array(0.0D, 0.0D), array(0.6D, 0.2D), 1)").collect()} == {0, 1}
    assert spark.sql("SELECT * FROM orthant_codes(3)").count() == 8


def test_filters_never_grow(spark):
    points = fixture(spark, "/root/testdata/sf0.001", "part2")
    sets = query_sets.sample_query_sets(points, 3, 3, 0.02)
    for predicate in (EpsRange(0.2), Nearest(40), DynamicSkyline()):
        n = {r["stage"]: r["n"] for r in explain_filters(points, sets, predicate, 16).collect()}
        assert n["results"] <= n["candidates"] and n["live sets"] <= n["sets"]
