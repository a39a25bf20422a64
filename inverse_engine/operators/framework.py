"""One entry for all predicates, regions, excluded members, linear top-k, and reports on methods."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import columns, coordinates, total
from inverse_engine.operators.eps_range import inverse_eps_range
from inverse_engine.operators.knn import inverse_knn
from inverse_engine.operators.skyline import inverse_dynamic_skyline
from inverse_engine.plans.blocks import Index
from inverse_engine.plans.store import stored
from inverse_engine.sources.points import dimension, lattice

STRATEGIES = ("joint", "single", "naive", "naive_at_once", "brute")


@dataclass(frozen=True)
class EpsRange:
    eps: float | None = None
    closed: bool = True


@dataclass(frozen=True)
class Nearest:
    k: int | None = None


@dataclass(frozen=True)
class DynamicSkyline:
    pass


def inverse(points: DataFrame, sets: DataFrame, predicate: EpsRange | Nearest | DynamicSkyline, strategy: str = "joint", candidates: DataFrame | None = None, include_query_objects: bool = False, index: Index | None = None, exclude_sets: DataFrame | None = None) -> DataFrame:
    """(set_id, id): the objects whose own query returns every member of the set, and none of the set's excluded members."""
    common = {"strategy": strategy, "candidates": candidates, "include_query_objects": include_query_objects, "index": index}
    if isinstance(predicate, EpsRange):
        run = lambda s: inverse_eps_range(points, s, predicate.eps, closed=predicate.closed, **common)
    elif isinstance(predicate, Nearest):
        run = lambda s: inverse_knn(points, s, predicate.k, **common)
    else:
        run = lambda s: inverse_dynamic_skyline(points, s, **common)
    found = run(sets)
    if exclude_sets is None:
        return found
    # An object goes if its own query returns any excluded member: each of them is a set of its own.
    extra = [c for c in exclude_sets.columns if c not in ("set_id", "q_id")]
    numbered = exclude_sets.groupBy("set_id", "q_id").agg(*[F.min(c).alias(c) for c in extra], F.lit(1).alias("one")).drop("one")
    numbered = stored(numbered.withColumn("n", F.monotonically_increasing_id()), "excluded-members")  # numbers are fixed as they are written
    alone = run(numbered.select(F.col("n").alias("set_id"), "q_id", *extra))
    owners = F.broadcast(numbered.select(F.col("n").alias("set_id"), F.col("set_id").alias("owner")))
    banned = alone.join(owners, "set_id").select(F.col("owner").alias("set_id"), "id").distinct()
    return found.join(banned, ["set_id", "id"], "left_anti")


def inverse_region(spark: SparkSession, points: DataFrame, sets: DataFrame, predicate, steps: int = 32) -> DataFrame:
    """(set_id, id) on a lattice of steps**d places over the unit box: the part of space that has all of Q in its result."""
    return inverse(points, sets, predicate, candidates=lattice(spark, dimension(points), steps))


def region_volume(region: DataFrame, d: int, steps: int) -> DataFrame:
    """(set_id, volume): the share of lattice places."""
    return region.groupBy("set_id").agg((F.count("*") / F.lit(float(steps**d))).alias("volume"))


def inverse_topk(points: DataFrame, weights: DataFrame, sets: DataFrame, k: int) -> DataFrame:
    """(set_id, id): weight vectors (id, w0..) under which all of Q are among the k points of the largest inner product (ties to
    the smaller id). A set of more than k members is empty; the member with the least score decides for all."""
    d = dimension(points)
    live = sets.join(sets.groupBy("set_id").agg(F.count("*").alias("m")).where(F.col("m") <= k), "set_id")
    w = columns(coordinates(d, "w"))
    x = columns(coordinates(d))
    score = total([a * b for a, b in zip(w, x, strict=True)])
    wide = weights.select(F.col("id").alias("w_id"), *w)
    members = F.broadcast(live.join(points, F.col("q_id") == F.col("id")).select("set_id", F.col("id").alias("q"), *x))
    worst = wide.join(members).select("set_id", "w_id", *w, F.struct((-score).alias("s"), "q").alias("key")).groupBy("set_id", "w_id", *w).agg(F.max("key").alias("worst"))
    ahead = (-score < F.col("worst.s")) | ((-score == F.col("worst.s")) & (F.col("id") < F.col("worst.q")))
    beaten = worst.join(F.broadcast(points) if points.count() <= 200_000 else points, ahead).groupBy("set_id", "w_id").agg(F.count("*").alias("n"))
    done = worst.select("set_id", "w_id").join(beaten, ["set_id", "w_id"], "left").where(F.coalesce("n", F.lit(0)) <= k - 1)
    return done.select("set_id", F.col("w_id").alias("id"))


def agreement(one: DataFrame, other: DataFrame) -> DataFrame:
    """(only_one, only_other, both): 0, 0 and the size of the result if two methods agree."""
    tagged = one.select("set_id", "id", F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(other.select("set_id", "id", F.lit(0).alias("a"), F.lit(1).alias("b")))
    each = tagged.groupBy("set_id", "id").agg(F.max("a").alias("a"), F.max("b").alias("b"))
    return each.agg(F.count_if((F.col("a") == 1) & (F.col("b") == 0)).alias("only_one"), F.count_if((F.col("a") == 0) & (F.col("b") == 1)).alias("only_other"), F.count_if((F.col("a") == 1) & (F.col("b") == 1)).alias("both"))


def cardinality(found: DataFrame, sets: DataFrame) -> DataFrame:
    """(n_sets, n_results, mean_results): empty sets count."""
    n = sets.select("set_id").distinct().agg(F.count("*").alias("n_sets"))
    return n.join(found.agg(F.count("*").alias("n_results"))).withColumn("mean_results", F.col("n_results") / F.col("n_sets"))
