"""Query sets: (set_id, q_id) rows, drawn in SQL-expressible ways, and one row with all coordinates for each set."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine.functions.geometry import columns, coordinates, dist2, in_box
from inverse_engine.sources.points import dimension


def draw(id_: Column, seed: int) -> Column:
    """A fixed pseudo-random order of ids."""
    return ((id_ % 2147483647) * 2654435761 + seed) % 4294967296


def anchors(points: DataFrame, n_sets: int, seed: int) -> DataFrame:
    """The first ids of the order, by rank: (set_id, a0..)."""
    d = dimension(points)
    first = points.withColumn("draw", draw(F.col("id"), seed)).orderBy("draw", "id").limit(n_sets)
    place = F.row_number().over(Window.orderBy("draw", "id")) - 1  # n_sets rows
    return first.select(place.alias("set_id"), F.col("id").alias("anchor"), *[F.col(f"x{i}").alias(f"a{i}") for i in range(d)])


def sample_query_sets(points: DataFrame, n_sets: int, m: int, extent: float, seed: int = 0, ranked: bool = False) -> DataFrame:
    """(set_id, q_id): an anchor and the first m - 1 others of the order inside the cube of volume `extent` around it. ranked: with r,
    the place in the set, from 1: the set of fewer members is that of the first places.

    A cube with too few points gives a smaller set. Anchors are n_sets rows, and cubes hold a fixed share of the points."""
    d = dimension(points)
    half = extent ** (1 / d) / 2
    centre = F.broadcast(anchors(points, n_sets, seed))
    x, a = columns(coordinates(d)), columns(coordinates(d, "a"))
    near = points.join(centre, in_box(x, [c - half for c in a], [c + half for c in a]))
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy((F.col("id") != F.col("anchor")).cast("int"), draw(F.col("id"), seed), "id"))
    return near.withColumn("r", rank).where(F.col("r") <= m).select(F.col("set_id").cast("long").alias("set_id"), F.col("id").alias("q_id"), *(["r"] if ranked else []))


def neighbour_query_sets(points: DataFrame, n_sets: int, m: int, seed: int = 0) -> DataFrame:
    """(set_id, q_id): an anchor and its m - 1 nearest neighbours by (squared distance, id)."""
    d = dimension(points)
    centre = F.broadcast(anchors(points, n_sets, seed))
    d2 = dist2(columns(coordinates(d)), columns(coordinates(d, "a")))
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy((F.col("id") != F.col("anchor")).cast("int"), "d2", "id"))
    return points.join(centre).withColumn("d2", d2).withColumn("r", rank).where(F.col("r") <= m).select(F.col("set_id").cast("long").alias("set_id"), F.col("id").alias("q_id"))


def attach_coordinates(points: DataFrame, sets: DataFrame) -> DataFrame:
    """(set_id, m, qs array<struct<q, x array<double>>>, further columns of `sets` by their least value). Members that are no points
    are left out here; operators.common.gathered raises for them. The sets are broadcast: gathered checks their size."""
    d = dimension(points)
    extra = [c for c in sets.columns if c not in ("set_id", "q_id")]
    found = points.join(F.broadcast(sets), F.col("q_id") == F.col("id")).where(F.col("set_id").isNotNull())
    member = F.struct(F.col("q_id").alias("q"), F.array(*columns(coordinates(d))).alias("x"))
    return found.groupBy("set_id").agg(F.array_sort(F.collect_set(member)).alias("qs"), *[F.min(c).alias(c) for c in extra]).withColumn("m", F.size("qs"))


def unknown_ids(points: DataFrame, sets: DataFrame) -> DataFrame:
    """Members of sets that are not ids of the points."""
    return sets.join(points, F.col("q_id") == F.col("id"), "left_anti")
