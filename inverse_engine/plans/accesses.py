"""Page accesses: which blocks each method asks for, with and without a buffer, for all three predicates.

Each method asks for the blocks that its filter leaves and for those that its refinement cannot count unread. Requests repeat;
with a buffer, a block is read once for each query set. The naive method's sets drop out when their intersection is empty."""

from __future__ import annotations

from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import all_of, at, box_min_dist2, columns, coordinates, dist2, max_dist2_of_set
from inverse_engine.operators import eps_range, knn, skyline
from inverse_engine.operators.common import chosen_member, gathered, iterated, without_queries
from inverse_engine.operators.framework import DynamicSkyline, EpsRange, Nearest, inverse
from inverse_engine.plans.blocks import Index, meeting
from inverse_engine.plans.store import stored, together

METHODS = ("joint", "single", "naive")


def _probed(found: DataFrame, index: Index, *keep: str) -> DataFrame:
    """Candidates with their coordinates, each as a query set of its own."""
    x = columns(coordinates(index.d))
    return found.join(index.points.drop("cell", "zone"), "id").withColumn("qs", F.array(F.struct(F.col("id").alias("q"), F.array(*x).alias("x")))).withColumn("m", F.lit(1)).select("set_id", "id", "qs", "m", *keep, *x)


def _eps_hits(index: Index, rows: DataFrame, closed: bool, *keep: str) -> DataFrame:
    """(set_id, keep.., cell): the blocks that meet the common window of the members of rows and come within eps of each."""
    d = index.d
    live = eps_range.eps_window(eps_range.eps_validate(rows, d, closed).where("alive"), d)
    live = live.select("set_id", *keep, "eps", "qs", F.col("lo").alias("w_lo"), F.col("hi").alias("w_hi"))

    def meets(lo: list[Column], hi: list[Column]) -> Column:
        window = all_of([(b >= u) & (a <= v) for a, b, u, v in zip(lo, hi, at(F.col("w_lo"), d), at(F.col("w_hi"), d), strict=True)])
        return window & (F.array_max(F.transform("qs", lambda q: box_min_dist2(lo, hi, at(q["x"], d)))) <= F.col("eps") * F.col("eps"))

    return stored(meeting(index, live, meets).select("set_id", *keep, "cell"), "access-blocks")


def _eps_near(index: Index, hit: DataFrame, rows: DataFrame) -> DataFrame:
    """The points of the blocks of `hit`, with the row of each set that asks for them."""
    asked = hit.select("set_id", F.col("cell").alias("hit_cell"))
    return index.read(hit).join(asked, F.col("cell") == F.col("hit_cell")).join(F.broadcast(rows), "set_id")


def _eps_requests(index: Index, rows: DataFrame, closed: bool, method: str) -> DataFrame:
    """(set_id, cell, times) of the range query's methods, all members of all sets in one batch."""
    d, once = index.d, F.lit(1).cast("long").alias("times")
    names = coordinates(d)
    x = columns(names)
    if method == "joint":
        return _eps_hits(index, rows, closed).select("set_id", "cell", once)
    if method == "naive":
        one = rows.select("set_id", "eps", F.posexplode("qs").alias("turn", "q")).select("set_id", "eps", "turn", F.array("q").alias("qs"), F.lit(1).alias("m"))
        hit = _eps_hits(index, one, closed, "turn")
        # A member's turn comes if some point is a result of all members before it: a point's turns are the members that it satisfies
        # from the first on.
        fails = lambda q, i: F.when(eps_range.within(dist2(x, at(q["x"], d)), F.col("eps"), closed), F.size("qs")).otherwise(i)
        turns = _eps_near(index, hit.where("turn = 0"), rows).select("set_id", F.array_min(F.transform("qs", fails)).alias("n")).groupBy("set_id").agg(F.max("n").alias("turns"))
        return hit.join(F.broadcast(turns), "set_id", "left").where(F.col("turn") <= F.coalesce("turns", F.lit(0))).select("set_id", "cell", once)
    one = chosen_member(rows, 0)
    hit = _eps_hits(index, one, closed)
    fits = eps_range.within(max_dist2_of_set(x, F.col("qs"), d), F.col("eps"), closed) & ~F.exists("all_qs", lambda q: q["q"] == F.col("id"))
    # Candidates of one place ask for the same blocks.
    places = stored(_eps_near(index, hit, one).where(fits).groupBy("set_id", "eps", *names).agg(F.count("*").alias("n")), "access-places")

    def meets(lo: list[Column], hi: list[Column]) -> Column:
        window = all_of([(b >= c - F.col("eps")) & (a <= c + F.col("eps")) for a, b, c in zip(lo, hi, x, strict=True)])
        return window & (box_min_dist2(lo, hi, x) <= F.col("eps") * F.col("eps"))

    spread = places.repartition(4 * index.points.sparkSession.sparkContext.defaultParallelism)
    again = meeting(index, spread, meets).groupBy("set_id", "cell").agg(F.sum("n").alias("times"))
    return hit.select("set_id", "cell", once).unionByName(again)


def _knn(index: Index, rows: DataFrame, joint: bool) -> tuple[DataFrame, DataFrame]:
    alive, _ = knn.alive_blocks(index, rows, joint)
    reached = stored(knn._candidates(index, rows, None, joint, False), "access-candidates")
    _, part = knn._refinement_reads(reached, index, False, True)
    return alive.unionByName(part.select("set_id", "cell")), knn._accepted(reached, index, False)


def _sky(index: Index, rows: DataFrame, joint: bool) -> tuple[DataFrame, DataFrame]:
    alive, _ = skyline.alive_blocks(index, rows)
    reached = stored(skyline._candidates(index, rows, None, False), "access-candidates")
    return alive.unionByName(skyline._mirror_reads(reached, index, True).select("set_id", "cell")), skyline._refined(reached, index, True)


def requests(index: Index, sets: DataFrame, predicate, method: str = "joint") -> DataFrame:
    """(set_id, cell), a row for each request of a block."""
    asked = _counted(index, gathered(index.points.drop("cell", "zone"), sets), predicate, method)
    return asked.select("set_id", "cell", F.explode(F.sequence(F.lit(1).cast("long"), F.col("times")))).drop("col")


def _counted(index: Index, rows: DataFrame, predicate, method: str) -> DataFrame:
    """(set_id, cell, times) for gathered rows: requests of a block, possibly in several rows."""
    if isinstance(predicate, EpsRange):
        if predicate.eps is not None:
            rows = rows.withColumn("eps", F.lit(float(predicate.eps)))
        return _eps_requests(index, rows, predicate.closed, method)
    return _requests(index, rows, predicate, method).groupBy("set_id", "cell").agg(F.count("*").alias("times"))


def _requests(index: Index, rows: DataFrame, predicate: Nearest | DynamicSkyline, method: str) -> DataFrame:
    if isinstance(predicate, Nearest):
        if predicate.k is not None:
            rows = rows.withColumn("k", F.lit(int(predicate.k)))
        rows = knn.knn_validate(rows).where("alive").drop("alive")
        run = lambda r, joint: _knn(index, r, joint)
    else:
        run = lambda r, joint: _sky(index, r, joint)
    if method == "joint":
        if isinstance(predicate, DynamicSkyline):
            rows = skyline.sky_validate(rows, index.d).where("alive").drop("alive")
        return run(rows, True)[0]
    if method == "naive":
        asked: list[DataFrame] = []

        def reverse(one: DataFrame) -> DataFrame:
            own, found = run(one, False)
            asked.append(stored(own, "access-requests"))
            return found

        iterated(rows, reverse)
        out = asked[0]
        for own in asked[1:]:
            out = out.unionByName(own)
        return out
    # The single filter: one member's reverse query, then each candidate's own query.
    one = chosen_member(rows, 0).drop("all_qs", "all_m")
    first, found = run(one, False)
    found = stored(without_queries(found, rows), "access-found")
    if isinstance(predicate, Nearest):
        again = None
        for k in [r[0] for r in rows.select("k").distinct().collect()]:  # the values of a sweep
            of = found.join(F.broadcast(rows.where(F.col("k") == k).select("set_id")), "set_id")
            read = knn.knn_reads(index, _probed(of, index).select("id", *coordinates(index.d)).distinct(), k).select(F.col("probe").alias("id"), "cell")
            own = of.join(read, "id").select("set_id", "cell")
            again = own if again is None else again.unionByName(own)
        again = first.limit(0) if again is None else again
    else:
        reached = _probed(found, index).drop("qs", "m").join(F.broadcast(rows.select("set_id", "qs")), "set_id")
        again = skyline._mirror_reads(reached, index, True).select("set_id", "cell")
    return first.unionByName(again)


def blocks_read(index: Index, sets: DataFrame, predicate, method: str = "joint") -> DataFrame:
    """(set_id, requested, read, pages): block requests with repetitions, without, and the pages of 1 KB that are read."""
    return _blocks_read(index, gathered(index.points.drop("cell", "zone"), sets), predicate, method)


def _blocks_read(index: Index, rows: DataFrame, predicate, method: str) -> DataFrame:
    asked = _counted(index, rows, predicate, method)
    once = asked.groupBy("set_id", "cell").agg(F.sum("times").alias("times")).join(index.blocks.select("cell", "cnt"), "cell")
    pages = F.ceil(F.col("cnt") * (8 * index.d + 8) / 1024)
    return once.groupBy("set_id").agg(F.sum("times").alias("requested"), F.count("*").alias("read"), F.sum(pages).cast("long").alias("pages"))


def averages(index: Index, sets: DataFrame, predicate, per: int) -> DataFrame:
    """(v, method, n_sets, requested, read, pages, results): means over the sets set_id = v * per + i of each v, sets without reads included."""
    sets = stored(sets, "access-sets")
    v = F.floor(F.col("set_id") / per).cast("int").alias("v")
    n = sets.select(v, "set_id").distinct().groupBy("v").agg(F.count("*").alias("n_sets"))
    points = index.points.drop("cell", "zone")
    rows = gathered(points, sets)
    runs = [lambda: inverse(points, rows, predicate, index=index).groupBy("set_id").agg(F.count("*").alias("found"))]
    runs += [partial(_blocks_read, index, rows, predicate, method) for method in METHODS]
    found, *read_by = together(points.sparkSession, runs, "access-sums")
    found = found.groupBy(v).agg(F.sum("found").alias("found"))
    out = None
    for method, sums in zip(METHODS, read_by, strict=True):
        read = sums.groupBy(v).agg(*[F.sum(c).alias(c) for c in ("requested", "read", "pages")])
        mean = [F.round(F.coalesce(c, F.lit(0)) / F.col("n_sets"), 6).alias(c) for c in ("requested", "read", "pages")]
        own = n.join(read, "v", "left").join(found, "v", "left").select("v", F.lit(method).alias("method"), "n_sets", *mean, F.round(F.coalesce("found", F.lit(0)) / F.col("n_sets"), 6).alias("results"))
        out = own if out is None else out.unionByName(own)
    return out


def ratios(averaged: DataFrame) -> DataFrame:
    """(v, method, times): how many times the joint method's pages each other method reads."""
    joint = averaged.where("method = 'joint'").select("v", F.col("pages").alias("least"))
    return averaged.where("method <> 'joint'").join(joint, "v").select("v", "method", F.round(F.col("pages") / F.greatest(F.col("least"), F.lit(1.0)), 3).alias("times"))


__all__ = ["averages", "blocks_read", "ratios", "requests"]
