"""Inverse range queries: the objects that have every member of Q within eps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import LONGEST_CHAIN, all_of, at, box_max_dist2, box_min_dist2, columns, coordinates, dist2, in_box, max_dist2_of_set
from inverse_engine.operators.common import chosen_member, gathered, intersected, iterated, singletons, without_queries
from inverse_engine.plans.blocks import Index
from inverse_engine.plans.store import stored
from inverse_engine.sources.points import dimension

#: Probes of a forward query, which are broadcast.
MOST_PROBES = 100_000


def within(d2: Column, eps: Column, closed: bool = True, times: float = 1.0) -> Column:
    limit = eps * eps * times
    return d2 <= limit if closed else d2 < limit


def eps_forward(points: DataFrame, probes: DataFrame, eps: float, closed: bool = True) -> DataFrame:
    """(probe, id): points within eps of each probe (id, x0..), the probe itself among them. Probes are broadcast: keep them few."""
    d = dimension(points)
    few = probes.limit(MOST_PROBES + 1).count()
    if few > MOST_PROBES:
        raise ValueError(f"more than {MOST_PROBES} probes; use an index's cells or split them")
    p = F.broadcast(probes.select(F.col("id").alias("probe"), *[F.col(c).alias(f"p_{c}") for c in coordinates(d)]))
    x, y = columns(coordinates(d)), columns(coordinates(d, "p_x"))
    box = in_box(x, [c - eps for c in y], [c + eps for c in y])
    return points.join(p, box & within(dist2(x, y), F.lit(eps), closed)).select("probe", "id")


def eps_validate(rows: DataFrame, d: int, closed: bool = True) -> DataFrame:
    """Adds alive: no two members are more than 2 eps apart (open balls: as far as 2 eps)."""
    far = F.array_max(F.transform("qs", lambda a: F.array_max(F.transform("qs", lambda b: dist2(at(a["x"], d), at(b["x"], d))))))
    return rows.withColumn("alive", within(far, F.col("eps"), closed, 4.0))


def eps_window(rows: DataFrame, d: int) -> DataFrame:
    """Adds lo, hi: the common box of the balls' bounding boxes."""
    ends = lambda i, f: f(F.transform("qs", lambda q: F.get(q["x"], F.lit(i))))
    return rows.withColumn("lo", F.array(*[ends(i, F.array_max) - F.col("eps") for i in range(d)])).withColumn("hi", F.array(*[ends(i, F.array_min) + F.col("eps") for i in range(d)]))


def eps_blocks(blocks: DataFrame, windows: DataFrame, d: int) -> DataFrame:
    """(set_id, cell, cnt, inner): blocks that meet the window and lie within eps of every member at their nearest place.

    inner: every point of the block is a result, so a count needs no read."""
    b = blocks.select("cell", F.col("lo").alias("b_lo"), F.col("hi").alias("b_hi"), "cnt")
    lo, hi = at(F.col("b_lo"), d), at(F.col("b_hi"), d)
    meets = all_of([(hi[i] >= F.get("lo", F.lit(i))) & (lo[i] <= F.get("hi", F.lit(i))) for i in range(d)])
    near = F.array_max(F.transform("qs", lambda q: box_min_dist2(lo, hi, at(q["x"], d))))
    far = F.array_max(F.transform("qs", lambda q: box_max_dist2(lo, hi, at(q["x"], d))))
    limit = F.col("eps") * F.col("eps")
    return b.join(F.broadcast(windows), meets & (near <= limit)).select("set_id", "cell", "cnt", (far < limit).alias("inner"))


def _reach(points: DataFrame, rows: DataFrame, d: int, closed: bool, index: Index | None) -> DataFrame:
    """(set_id, id) for gathered rows with eps, members of Q among them."""
    live = eps_validate(rows, d, closed).where("alive").drop("alive")
    x = columns(coordinates(d))
    fits = within(max_dist2_of_set(x, F.col("qs"), d), F.col("eps"), closed)
    # Objects prune nothing here: whether one is a result does not depend on the others. The filter is of the query's members only.
    if index is None and d > LONGEST_CHAIN:  # boxes say little in many dimensions
        return points.join(F.broadcast(live), fits).select("set_id", "id")
    live = eps_window(live, d)
    if index is None:
        window = in_box(x, at(F.col("lo"), d), at(F.col("hi"), d))
        return points.join(F.broadcast(live), window & fits).select("set_id", "id")
    hit = stored(eps_blocks(index.blocks, live, d).select(F.col("set_id").alias("owner_set"), F.col("cell").alias("hit_cell")), "eps-blocks")
    return index.read(hit.select(F.col("hit_cell").alias("cell"))).join(hit, F.col("cell") == F.col("hit_cell")).join(F.broadcast(live), F.col("owner_set") == F.col("set_id")).where(fits).select("set_id", "id")


def inverse_eps_range(points: DataFrame, sets: DataFrame, eps: float | None = None, strategy: str = "joint", closed: bool = True, include_query_objects: bool = False, candidates: DataFrame | None = None, index: Index | None = None, seed: int = 0) -> DataFrame:
    """(set_id, id). `sets` may hold a column eps; candidates: the objects to choose from, if not the points themselves."""
    d = dimension(points)
    rows = gathered(points, sets)
    if eps is not None:
        rows = rows.withColumn("eps", F.lit(float(eps)))
    pool = points if candidates is None else candidates
    if strategy == "joint":
        found = _reach(pool, rows, d, closed, index)
    elif strategy == "brute":
        fits = F.forall("qs", lambda q: within(dist2(columns(coordinates(d)), at(q["x"], d)), F.col("eps"), closed))
        found = pool.join(F.broadcast(rows), fits).select("set_id", "id")
    elif strategy == "naive":
        found = iterated(rows, lambda one: _reach(pool, one, d, closed, index))
    elif strategy == "naive_at_once":
        each = _reach(pool, singletons(rows), d, closed, index)
        found = intersected(each.join(F.broadcast(rows.select(F.col("set_id").alias("w"), F.col("m").alias("owner_m"))), F.col("set_id.owner") == F.col("w")).select(F.col("set_id.owner").alias("owner"), "owner_m", "id"))
    elif strategy == "single":
        one = chosen_member(rows, seed)
        reached = _reach(pool, one, d, closed, index)
        back = reached.join(F.broadcast(one.select("set_id", F.col("all_qs").alias("all"), "eps")), "set_id").join(pool, "id")
        found = back.where(F.forall("all", lambda q: within(dist2(columns(coordinates(d)), at(q["x"], d)), F.col("eps"), closed))).select("set_id", "id")
    else:
        raise ValueError(strategy)
    return found if include_query_objects or candidates is not None else without_queries(found, rows)


def inverse_eps_vectors(vectors: DataFrame, sets: DataFrame, eps: float) -> DataFrame:
    """(set_id, id) for points (id, v array<double>) of many dimensions, where boxes say little: one pass, no unrolled columns."""
    member = F.struct(F.col("q_id").alias("q"), F.col("v").alias("x"))
    rows = F.broadcast(sets).join(vectors, F.col("q_id") == F.col("id")).groupBy("set_id").agg(F.collect_list(member).alias("qs"))
    far2 = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    limit = F.lit(eps) * F.lit(eps)
    live = rows.where(F.forall("qs", lambda a: F.forall("qs", lambda b: far2(a["x"], b["x"]) <= limit * 4)))
    fits = F.forall("qs", lambda q: (far2(F.col("v"), q["x"]) <= limit) & (q["q"] != F.col("id")))
    return vectors.join(F.broadcast(live), fits).select("set_id", "id")


def eps_result_counts(index: Index, sets: DataFrame, eps: float) -> DataFrame:
    """(set_id, n): numbers of results with members of Q among them; inner blocks are counted unread."""
    rows = gathered(index.points.drop("cell"), sets).withColumn("eps", F.lit(float(eps)))
    live = eps_window(eps_validate(rows, index.d).where("alive"), index.d)
    hit = stored(eps_blocks(index.blocks, live, index.d), "eps-blocks")
    whole = hit.where("inner").groupBy("set_id").agg(F.sum("cnt").alias("n"))
    part = hit.where(~F.col("inner")).select(F.col("set_id").alias("s"), F.col("cell").alias("hit_cell"))
    fits = within(max_dist2_of_set(columns(coordinates(index.d)), F.col("qs"), index.d), F.col("eps"))
    read = index.read(part.select(F.col("hit_cell").alias("cell"))).join(part, F.col("cell") == F.col("hit_cell")).join(F.broadcast(live), F.col("s") == F.col("set_id")).where(fits).groupBy("set_id").agg(F.count("*").alias("n"))
    return whole.unionByName(read).groupBy("set_id").agg(F.sum("n").alias("n"))


__all__ = ["eps_blocks", "eps_forward", "eps_result_counts", "eps_validate", "eps_window", "inverse_eps_range"]
