"""What the three predicates share: the table of query sets, singletons, result shaping."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.plans.store import stored
from inverse_engine.sources.query_sets import attach_coordinates

#: Query sets of a batch, and members in all, that one plan broadcasts; more are run in batches.
MOST_SETS, MOST_MEMBERS = 20_000, 500_000


def gathered(points: DataFrame, sets: DataFrame) -> DataFrame:
    """One row for each set, written once: at most MOST_SETS rows and MOST_MEMBERS members. Members that are no points raise. Rows that
    are gathered already stay as they are, so that several runs over the same points share them."""
    if "qs" in sets.columns:
        return sets
    sets = stored(sets, "query-members")
    asked = sets.groupBy("set_id").agg(F.count_distinct("q_id").alias("asked"))
    size = asked.agg(F.count("*").alias("n"), F.coalesce(F.sum("asked"), F.lit(0)).alias("members")).first()
    if size["n"] > MOST_SETS or size["members"] > MOST_MEMBERS:
        raise ValueError(f"{size['n']} query sets of {size['members']} members; split the batch")
    rows = stored(attach_coordinates(points, sets), "query-sets")
    lost = asked.join(F.broadcast(rows.select("set_id", "m")), "set_id", "left").where(F.coalesce("m", F.lit(0)) != F.col("asked")).head(1)
    if lost:
        raise ValueError(f"set {lost[0]['set_id']} has members that are no points; unknown_ids() lists them")
    return rows


def singletons(rows: DataFrame) -> DataFrame:
    """Each member of each gathered set as a set of its own; set_id becomes (owner, member) and `owner` is kept."""
    one = rows.select(F.col("set_id").alias("owner"), F.col("m").alias("owner_m"), F.explode("qs").alias("one"), *[c for c in rows.columns if c not in ("set_id", "m", "qs")])
    return one.withColumn("set_id", F.struct("owner", F.col("one.q").alias("q"))).withColumn("qs", F.array("one")).withColumn("m", F.lit(1)).drop("one")


def without_queries(found: DataFrame, rows: DataFrame) -> DataFrame:
    """(set_id, id) without members of the set: queries are no results unless asked for."""
    members = rows.select("set_id", F.explode("qs.q").alias("id"))
    return found.join(F.broadcast(members), ["set_id", "id"], "left_anti")


def intersected(per_query: DataFrame) -> DataFrame:
    """Results that all members' reverse queries share, from (owner, owner_m, q, id)."""
    return per_query.groupBy("owner", "id").agg(F.count("*").alias("n"), F.first("owner_m").alias("owner_m")).where(F.col("n") == F.col("owner_m")).select(F.col("owner").alias("set_id"), "id")


def chosen_member(rows: DataFrame, seed: int) -> DataFrame:
    """The singleton of each set that a hash of (member, seed) picks: the single filter's query."""
    order = F.array_min(F.transform("qs", lambda q: F.struct(F.xxhash64(q["q"], F.lit(seed)).alias("h"), q.alias("one"))))
    return rows.withColumn("all_qs", F.col("qs")).withColumn("all_m", F.col("m")).withColumn("qs", F.array(order["one"])).withColumn("m", F.lit(1))


def iterated(rows: DataFrame, reverse: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(set_id, id) that the members' reverse queries share, one member of every set at a time: sets whose intersection is empty
    drop out, and nothing runs when none is left. `reverse` takes rows with one member each."""
    found, turn = None, 0
    most = rows.agg(F.max("m")).first()[0] or 0
    while turn < most:
        live = rows.where(F.col("m") > turn)
        if found is not None:
            live = live.join(F.broadcast(found.select("set_id").distinct()), "set_id", "left_semi")
        one = live.withColumn("qs", F.slice("qs", F.lit(turn + 1), F.lit(1))).withColumn("m", F.lit(1))
        got = reverse(one)
        if found is not None:
            shorter = found.join(F.broadcast(rows.where(F.col("m") <= turn).select("set_id")), "set_id", "left_semi")
            got = found.join(got, ["set_id", "id"], "left_semi").unionByName(shorter)
        found = stored(got, "intersection")
        turn += 1
        if not found.head(1):
            break
    return found if found is not None else rows.select("set_id", F.lit(0).cast("long").alias("id")).where("false")
