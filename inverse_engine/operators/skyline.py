"""Inverse dynamic skyline queries: the objects whose dynamic skyline holds all of Q."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine.functions.geometry import all_of, any_of, at, box_in_pruning_region, box_max_dist2, columns, coordinates, dominates, in_pruning_region, orthant
from inverse_engine.operators.common import chosen_member, gathered, intersected, iterated, singletons, without_queries
from inverse_engine.plans.blocks import Index, build_index, meeting
from inverse_engine.plans.store import stored
from inverse_engine.sources.points import dimension

#: Points near Q that prune candidates of each set: around each member, so many of each orthant. Probes of a forward query at most.
PRUNERS, MOST_PROBES = 6, 20_000
#: Dimensions up to which orthants are tested for members.
MOST_ORTHANTS = 5
#: Points that are read near a member for each place that shall prune: places may hold many copies.
COPIES = 64
#: Points that the definition broadcasts, so that an object's test ends at the first that blocks it.
MOST_BROADCAST = 2_000_000
#: Points that rule out candidates before any block is looked up, about; candidates, and points, that are compared at once.
FIRST_POINTS, STEP, POINTS_AT_ONCE = 8_192, 2_048, 256
#: What rounding may move a midpoint by, as a share of its terms (a little more than it does).
SLACK = 1e-12


def _undominated(x: np.ndarray) -> np.ndarray:
    """Places of the rows that no row is at most in all and less in one column."""
    order = np.lexsort((*x.T[::-1], x.sum(axis=1)))
    kept: list[int] = []
    for i in order.tolist():
        k = x[kept]
        if not len(kept) or not (np.all(k <= x[i], axis=1) & np.any(k < x[i], axis=1)).any():
            kept.append(i)
    return np.array(sorted(kept), dtype=np.int64)


def skyline(points: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Rows (id, x0.. and the columns `by`) that no other row of their group dominates. First inside each partition, then what is left by group."""
    d = dimension(points)
    names, by = coordinates(d), by or []
    keep = points.select(*by, "id", *names)

    def local(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for frame in frames:
            held = frame if held is None else pd.concat([held, frame], ignore_index=True)
            parts = [g.iloc[_undominated(g[names].to_numpy())] for _, g in (held.groupby(by, sort=False) if by else [(0, held)])]
            held = pd.concat(parts, ignore_index=True) if parts else held
        if held is not None:
            yield held

    def merge(frame: pd.DataFrame) -> pd.DataFrame:
        return frame.iloc[_undominated(frame[names].to_numpy())]

    return keep.mapInPandas(local, keep.schema).groupBy(*by).applyInPandas(merge, keep.schema)


def dynamic_skyline(points: DataFrame, probes: DataFrame) -> DataFrame:
    """(probe, id): the points that no other point beats at every |x - probe|; the probe's own id does not count.

    Probes are broadcast, and each is paired with all points: more than MOST_PROBES raise."""
    d = dimension(points)
    if probes.limit(MOST_PROBES + 1).count() > MOST_PROBES:
        raise ValueError(f"more than {MOST_PROBES} probes; refine by mirror boxes instead")
    p = F.broadcast(probes.select(F.col("id").alias("probe"), *[F.col(c).alias(f"p_{c}") for c in coordinates(d)]))
    moved = points.join(p, F.col("id") != F.col("probe")).select("probe", "id", *[F.abs(F.col(c) - F.col(f"p_{c}")).alias(c) for c in coordinates(d)])
    return skyline(moved, ["probe"]).select("probe", "id")


def rds_candidates(points: DataFrame, rows: DataFrame) -> DataFrame:
    """(set_id, id): for a single member q, the union of the skylines, by distance to q, of the orthants around q."""
    d = dimension(points)
    x, q = columns(coordinates(d)), at(F.get("qs", F.lit(0))["x"], d)
    near = points.join(F.broadcast(rows), F.col("id") != F.get("qs", F.lit(0))["q"])
    key = F.col("set_id").cast("string")  # a set's id may be a struct, which pandas cannot group by
    moved = near.select(key.alias("key"), orthant(x, q).alias("orthant"), "id", *[F.abs(a - b).alias(n) for a, b, n in zip(x, q, coordinates(d), strict=True)])
    return skyline(moved, ["key", "orthant"]).join(F.broadcast(rows.select("set_id", key.alias("key"))), "key").select("set_id", "id")


def sky_validate(rows: DataFrame, d: int) -> DataFrame:
    """Adds alive: false if all closed orthants around a member hold another member elsewhere.

    Beyond MOST_ORTHANTS dimensions all sets stay alive: 2**d orthants are seldom full, and the test is only a shortcut."""
    if d > MOST_ORTHANTS:
        return rows.withColumn("alive", F.lit(True))

    def surrounded(q):
        others = F.filter("qs", lambda o: ~all_of([a == b for a, b in zip(at(o["x"], d), at(q["x"], d), strict=True)]))

        def held(mask: int):
            return F.exists(others, lambda o: all_of([(a >= b) if mask >> i & 1 else (a <= b) for i, (a, b) in enumerate(zip(at(o["x"], d), at(q["x"], d), strict=True))]))

        return all_of([held(mask) for mask in range(1 << d)])

    return rows.withColumn("alive", ~F.exists("qs", surrounded))


def pair_pruned(p: list, d: int):
    """Is the point inside the region of any ordered pair of members?"""
    return F.exists("qs", lambda q: F.exists("qs", lambda o: (o["q"] != q["q"]) & in_pruning_region(at(q["x"], d), at(o["x"], d), p)))


def sky_query_prune(points: DataFrame, rows: DataFrame, d: int) -> DataFrame:
    """(set_id, id): points, members of the set aside, that no pair of members prunes."""
    own = F.exists("qs", lambda q: q["q"] == F.col("id"))
    return points.join(F.broadcast(rows), ~own & ~pair_pruned(columns(coordinates(d)), d)).select("set_id", "id")


def staircases(rows: DataFrame) -> DataFrame:
    """For two dimensions: (set_id, steps): corners (direction, x, y) of the pairs' regions that no other corner of their direction
    covers. A missing bound is infinite; corners with different free dimensions are not compared. Corners lie a little further out
    than the midpoints, as sums of doubles are rounded in another way than distances are."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for set_id, qs in zip(frame["set_id"], frame["qs"], strict=True):
            found: dict[tuple, set] = {}
            for a in qs:
                for b in qs:
                    sign = tuple(int(np.sign(v - u)) for u, v in zip(a["x"], b["x"], strict=True))
                    if a["q"] != b["q"] and any(sign):
                        found.setdefault(sign, set()).add(tuple(s * (u + v) - SLACK * (abs(u) + abs(v)) if s else -np.inf for s, u, v in zip(sign, a["x"], b["x"], strict=True)))
            steps = []
            for sign, corners in found.items():
                best = np.inf
                for x, y in sorted(corners):
                    if y < best or x == -np.inf:
                        steps.append({"sx": sign[0], "sy": sign[1], "x": float(x), "y": float(y)})
                        best = min(best, y)
            out.append((set_id, steps))
        return pd.DataFrame(out, columns=["set_id", "steps"])

    return rows.select("set_id", "qs").groupBy("set_id").applyInPandas(build, "set_id long, steps array<struct<sx:int,sy:int,x:double,y:double>>")


def staircase_pruned(p: list):
    """As pair_pruned, in two dimensions: points outside all reduced corners are left alone at once, and the pairs, by the distances
    themselves, decide the others, so that a point on the midline of two members is judged by its definition."""
    x, y = p
    beyond = lambda sign, v, corner: (sign == 0) | (sign * v * 2 + F.abs(v) * SLACK >= corner)
    return F.exists("steps", lambda s: beyond(s["sx"], x, s["x"]) & beyond(s["sy"], y, s["y"])) & pair_pruned(p, 2)


def _prunable(index: Index, rows: DataFrame, d: int) -> DataFrame:
    """rows with `pruners`: around each member, the PRUNERS places of each orthant that are nearest by their largest difference, with
    one point each: copies of a member prune nothing, and copies of a pruner nothing more.

    They come from the blocks within the distance that holds enough points in all; orthants beyond MOST_ORTHANTS dimensions are one,
    with as many places as all orthants have together."""
    x = columns(coordinates(d))
    many = PRUNERS << min(d, MOST_ORTHANTS)
    one = rows.select("set_id", F.explode("qs").alias("member"))
    asked = one.select("set_id", F.col("member.q").alias("owner"), F.col("member.x").alias("at"))
    here = at(F.col("at"), d)
    lo, hi = at(F.col("lo"), d), at(F.col("hi"), d)
    order = F.sum("cnt").over(Window.partitionBy("set_id", "owner").orderBy("far", "cell"))
    ranked = index.blocks.join(F.broadcast(asked)).withColumn("far", box_max_dist2(lo, hi, here)).withColumn("upto", order)
    blocks = stored(ranked.where(F.col("upto") - F.col("cnt") <= many * COPIES).select("set_id", "owner", "at", "cell"), "sky-near-blocks")
    near = index.read(blocks).join(F.broadcast(blocks), "cell").where((F.col("id") != F.col("owner")) & any_of([a != b for a, b in zip(x, here, strict=True)]))
    near = near.groupBy("set_id", "owner", "at", *coordinates(d)).agg(F.min("id").alias("id"))
    part = orthant(x, here) if d <= MOST_ORTHANTS else F.lit(0)
    ranked = near.select("set_id", "owner", "id", F.array(*x).alias("x"), part.alias("part"), F.greatest(*[F.abs(a - b) for a, b in zip(x, here, strict=True)], F.lit(0.0)).alias("far"))
    nearest = F.row_number().over(Window.partitionBy("set_id", "owner", "part").orderBy("far", "id"))
    packed = ranked.withColumn("r", nearest).where(F.col("r") <= (PRUNERS if d <= MOST_ORTHANTS else many)).groupBy("set_id").agg(F.collect_set(F.struct(F.col("id").alias("q"), "x")).alias("pruners"))
    return rows.join(packed, "set_id", "left").withColumn("pruners", F.coalesce("pruners", F.array().cast("array<struct<q:bigint,x:array<double>>>")))


def _mirror_reads(reached: DataFrame, index: Index, mono: bool) -> DataFrame:
    """(set_id, c, q, c_x.., cell): the blocks that meet the box between each member and its mirror image through each candidate."""
    d = index.d
    names = coordinates(d)
    c = reached.select("set_id", F.col("id").alias("c"), F.explode("qs").alias("q"), *[F.col(n).alias(f"c_{n}") for n in names]).where((F.col("q.q") != F.col("c")) if mono else F.lit(True))
    y, q = columns(coordinates(d, "c_x")), at(F.col("q.x"), d)
    # A block that ends at the mirror box's very side must not be lost by rounding.
    reach = [F.abs(a - b) * (1 + SLACK) + F.abs(b) * SLACK for a, b in zip(q, y, strict=True)]
    return meeting(index, c, lambda lo, hi: all_of([(h >= a - r) & (l <= a + r) for l, h, a, r in zip(lo, hi, y, reach, strict=True)])).select("set_id", "c", "q", *y, "cell")


def _numbered(rows: DataFrame) -> DataFrame:
    """rows with a number of each set, `set_no`, which is fixed when they are written."""
    return rows.withColumn("set_no", F.monotonically_increasing_id())


def _arrays(rows: DataFrame) -> dict[int, dict[str, np.ndarray]]:
    """By number of a set: its members (q, x) and, where rows have them, its pruners (near_q, near_x). They reach the driver and all tasks,
    as what is broadcast does."""
    out = {}
    for r in rows.select("set_no", *[c for c in ("qs", "pruners") if c in rows.columns]).collect():
        out[r["set_no"]] = one = {}
        for column, q, x in (("qs", "q", "x"), ("pruners", "near_q", "near_x")):
            if column in r:
                one[q] = np.array([p["q"] for p in r[column]], dtype=np.int64)
                one[x] = np.array([p["x"] for p in r[column]], dtype=np.float64).reshape(len(r[column]), -1)
    return out


def _barred(ids: np.ndarray, x: np.ndarray, q: np.ndarray, q_x: np.ndarray, other: np.ndarray, other_x: np.ndarray, mono: bool) -> np.ndarray:
    """Which objects (ids, x) see some member (q, q_x) dominated by one of the others, neither being the object itself."""
    out = np.zeros(len(ids), dtype=bool)
    for member, place in zip(q, q_x, strict=True):
        left = np.flatnonzero(~out & (ids != member) if mono else ~out)
        for i in range(0, len(other), POINTS_AT_ONCE):
            if not len(left):
                break
            o, o_x, c = other[i : i + POINTS_AT_ONCE], other_x[i : i + POINTS_AT_ONCE], x[left]
            most, less = np.broadcast_to(o != member, (len(left), len(o))).copy(), np.zeros((len(left), len(o)), dtype=bool)
            if mono:
                most &= o[None] != ids[left][:, None]
            for j in range(x.shape[1]):
                gap, reach = np.abs(o_x[None, :, j] - c[:, None, j]), np.abs(place[j] - c[:, None, j])
                most &= gap <= reach
                less |= gap < reach
            hit = (most & less).any(axis=1)
            out[left[hit]] = True
            left = left[~hit]
    return out


def _filtered(near: DataFrame, sets: dict[int, dict[str, np.ndarray]], test: Callable[[dict, np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """Rows of near (set_no, id, .., x..) that pass the test of their set: test(set, ids, places)."""
    names = coordinates(dimension(near))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            passed = np.zeros(len(frame), dtype=bool)
            ids, x = frame["id"].to_numpy(), frame[names].to_numpy(dtype=np.float64)
            for i, all_ in frame.groupby("set_no", sort=False).indices.items():
                for start in range(0, len(all_), STEP):
                    place = all_[start : start + STEP]
                    passed[place] = test(sets[i], ids[place], x[place])
            yield frame[passed]

    # Small tables lie in few files: all cores take part.
    return near.repartition(2 * near.sparkSession.sparkContext.defaultParallelism).mapInPandas(run, near.schema)


def _not_ruled_out(reached: DataFrame, index: Index, mono: bool) -> DataFrame:
    """Candidates that none of about FIRST_POINTS points bars from a member's side: whatever the other points are, those that go are no
    results. All that are left meet every point that could bar them; the points looked at first decide how many those are, not which."""
    n = index.blocks.agg(F.sum("cnt")).first()[0] or 0
    if n <= FIRST_POINTS:
        return reached
    names = coordinates(index.d)
    first = index.points.where(F.pmod(F.xxhash64("id"), F.lit(n // FIRST_POINTS)) == 0).limit(2 * FIRST_POINTS).select("id", *names).toPandas()
    other, other_x = first["id"].to_numpy(), first[names].to_numpy(dtype=np.float64)
    rows = stored(_numbered(reached.groupBy("set_id").agg(F.first("qs").alias("qs"))), "sky-asked-sets")
    near = reached.join(F.broadcast(rows.select("set_id", "set_no")), "set_id").select("set_no", "id", *[c for c in reached.columns if c == "cell"], *names)
    left = _filtered(near, _arrays(rows), lambda one, ids, x: ~_barred(ids, x, one["q"], one["x"], other, other_x, mono))
    return stored(left.join(F.broadcast(rows), "set_no").select(*reached.columns), "sky-not-ruled-out")


def _unblocked(reached: DataFrame, index: Index, mono: bool) -> DataFrame:
    """Candidates that neither some points of the table nor, as nearest points block most, those of their own block bar from a member's
    side, stored: few are left for the mirror boxes, which are large."""
    d = index.d
    y, q, x = columns(coordinates(d, "c_x")), at(F.col("q.x"), d), columns(coordinates(d))
    reached = _not_ruled_out(stored(reached, "sky-candidates"), index, mono)
    if "cell" not in reached.columns:
        return reached
    each = reached.select("cell", "set_id", F.col("id").alias("c"), F.explode("qs").alias("q"), *[F.col(n).alias(f"c_{n}") for n in coordinates(d)]).where(F.col("q.q") != F.col("c"))
    near = index.read(reached.select("cell")).select(F.col("cell").alias("near_cell"), "id", *x)
    barred = (F.col("cell") == F.col("near_cell")) & (F.col("id") != F.col("q.q")) & (F.col("id") != F.col("c")) & dominates(x, q, y)
    blocked = each.join(near, barred, "left_semi").select("set_id", F.col("c").alias("id")).distinct()
    return stored(reached.join(blocked, ["set_id", "id"], "left_anti"), "sky-unblocked")


def _refined(reached: DataFrame, index: Index, mono: bool) -> DataFrame:
    """(set_id, id) of candidates (set_id, qs, id, x.., cell if they are of the index) none of whose mirror boxes holds a blocker."""
    d = index.d
    y, q, x = columns(coordinates(d, "c_x")), at(F.col("q.x"), d), columns(coordinates(d))
    other = (F.col("id") != F.col("q.q")) & ((F.col("id") != F.col("c")) if mono else F.lit(True))
    reached = _unblocked(reached, index, mono)
    # As many tasks whatever the tables' bytes are: it is pairs that take the time.
    tasks = 4 * index.points.sparkSession.sparkContext.defaultParallelism
    reads = _mirror_reads(reached, index, mono).repartition(tasks, "cell")
    blocked = reads.join(index.points.repartition(tasks, "cell"), "cell").where(other & dominates(x, q, y)).select("set_id", F.col("c").alias("id")).distinct()
    return reached.select("set_id", "id").join(blocked, ["set_id", "id"], "left_anti")


def _searched(reached: DataFrame, index: Index, mono: bool) -> DataFrame:
    """Refinement by a dynamic skyline for each candidate, which must hold all of Q. What could keep a member out of it lies in the
    mirror boxes, so a candidate's skyline is taken of the points there, the members among them."""
    d = index.d
    names, x, y = coordinates(d), columns(coordinates(d)), columns(coordinates(d, "c_x"))
    reached = _unblocked(reached, index, mono)
    reads = _mirror_reads(reached, index, mono).select("set_id", "c", *y, F.col("q.x").alias("q_x"), "cell")
    held = all_of([F.abs(a - b) <= F.abs(q - b) for a, b, q in zip(x, y, at(F.col("q_x"), d), strict=True)])
    near = reads.join(index.points, "cell").where(held & ((F.col("id") != F.col("c")) if mono else F.lit(True)))
    moved = near.select("set_id", F.col("c").alias("probe"), "id", *[F.abs(a - b).alias(n) for n, a, b in zip(names, x, y, strict=True)]).distinct()
    found = skyline(moved, ["set_id", "probe"]).select("set_id", "probe", "id")
    wanted = reached.select("set_id", F.col("id").alias("probe"), F.explode("qs.q").alias("id"))
    wanted = wanted.where(F.col("id") != F.col("probe")) if mono else wanted
    lost = wanted.join(found, ["set_id", "probe", "id"], "left_anti").select("set_id", F.col("probe").alias("id")).distinct()
    return reached.select("set_id", "id").join(lost, ["set_id", "id"], "left_anti")


def alive_blocks(index: Index, rows: DataFrame, include_query_objects: bool = False) -> tuple[DataFrame, DataFrame]:
    """(set_id, cell) of the blocks that neither a pair of members nor a point near Q prunes whole, and rows with those points."""
    d = index.d
    rows = stored(_numbered(_prunable(index, rows, d)), "sky-armed-sets")
    lo, hi = at(F.col("lo"), d), at(F.col("hi"), d)
    # A pruner inside the block would prune all but itself, so only those outside its box count.
    outside = lambda o: any_of([(v < a) | (v > b) for v, a, b in zip(at(o["x"], d), lo, hi, strict=True)])
    gone = F.exists("qs", lambda q: F.exists("qs", lambda o: (o["q"] != q["q"]) & box_in_pruning_region(at(q["x"], d), at(o["x"], d), lo, hi)))
    shot = F.exists("pruners", lambda o: outside(o) & F.exists("qs", lambda q: (q["q"] != o["q"]) & box_in_pruning_region(at(q["x"], d), at(o["x"], d), lo, hi)))
    kept = index.blocks.join(F.broadcast(rows), F.lit(include_query_objects) | ~(gone | shot)).select("set_id", "cell")
    return stored(kept, "sky-alive-blocks"), rows


def _candidates(index: Index, rows: DataFrame, pool: DataFrame | None, include_query_objects: bool) -> DataFrame:
    """(set_id, qs, id, x.., and cell where they are the index's points) that no filter removes."""
    names = coordinates(index.d)
    if pool is None:
        kept, rows = alive_blocks(index, rows, include_query_objects)
        near = index.read(kept).join(kept, "cell").join(F.broadcast(rows.select("set_id", "set_no")), "set_id").select("set_no", "id", "cell", *names)
    else:
        rows = stored(_numbered(_prunable(index, rows, index.d)), "sky-armed-sets")
        near = pool.join(F.broadcast(rows.select("set_no"))).select("set_no", "id", *names)
    sets, mono = _arrays(rows), pool is None

    def left(one: dict, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        own = np.isin(ids, one["q"]) if mono else np.zeros(len(ids), dtype=bool)
        kept = np.ones(len(ids), dtype=bool) if include_query_objects else ~own
        for others, other_x, of in (("q", "x", ~own), ("near_q", "near_x", True)):  # pairs of members prune no member
            at_ = np.flatnonzero(kept & of)
            kept[at_[_barred(ids[at_], x[at_], one["q"], one["x"], one[others], one[other_x], mono)]] = False
        return kept

    return _filtered(near, sets, left).join(F.broadcast(rows.select("set_no", "set_id", "qs")), "set_no").select("set_id", "qs", "id", *names, *near.columns[2 : -index.d])


def inverse_dynamic_skyline(points: DataFrame, sets: DataFrame, strategy: str = "joint", include_query_objects: bool = False, candidates: DataFrame | None = None, index: Index | None = None, refine: str = "mbr", seed: int = 0) -> DataFrame:
    """(set_id, id). A member of Q as a candidate is tested against the other members only."""
    d = dimension(points)
    rows = gathered(points, sets)
    mono = candidates is None
    pool = points if mono else candidates
    if strategy == "brute":
        names = coordinates(d)
        own = F.exists("qs", lambda q: q["q"] == F.col("id")) if mono else F.lit(False)
        asked = pool.join(F.broadcast(rows), F.lit(include_query_objects) | ~own).select("set_id", "id", F.explode("qs").alias("q"), *[F.col(n).alias(f"c_{n}") for n in names]).where((F.col("q.q") != F.col("id")) if mono else F.lit(True))
        o = points.select(F.col("id").alias("o"), *names)
        beats = (F.col("o") != F.col("q.q")) & ((F.col("o") != F.col("id")) if mono else F.lit(True)) & dominates(columns(names), at(F.col("q.x"), d), columns(coordinates(d, "c_x")))
        if points.count() <= MOST_BROADCAST:
            lost = asked.join(F.broadcast(o), beats, "left_semi").select("set_id", "id").distinct()
        else:
            lost = asked.join(o, beats).select("set_id", "id").distinct()
        return asked.select("set_id", "id").distinct().join(lost, ["set_id", "id"], "left_anti")
    index = index or build_index(points)
    if strategy == "joint":
        live = sky_validate(rows, d)
        live = (live if include_query_objects else live.where("alive")).drop("alive")
        reached = _candidates(index, live, candidates, include_query_objects)
        return _searched(reached, index, mono) if refine == "dsl" else _refined(reached, index, mono)
    reverse = lambda one: _refined(_candidates(index, one, candidates, False), index, mono)
    if strategy == "naive":
        found = iterated(rows, reverse)
        return without_queries(found, rows) if mono else found
    if strategy == "naive_at_once":
        each = reverse(singletons(rows))
        owners = F.broadcast(rows.select(F.col("set_id").alias("w"), F.col("m").alias("owner_m")))
        found = intersected(each.join(owners, F.col("set_id.owner") == F.col("w")).select(F.col("set_id.owner").alias("owner"), "owner_m", "id"))
        return without_queries(found, rows) if mono else found
    if strategy == "single":
        reached = reverse(chosen_member(rows, seed).drop("all_qs", "all_m"))
        if mono:
            reached = without_queries(reached, rows)
        back = reached.join(F.broadcast(rows), "set_id").join(pool, "id").select("set_id", "qs", "id", *coordinates(d))
        return _searched(back, index, mono) if refine == "dsl" else _refined(back, index, mono)
    raise ValueError(strategy)


def reverse_dynamic_skyline(points: DataFrame, sets: DataFrame, index: Index | None = None, by: str = "blocks") -> DataFrame:
    """(set_id, id) for sets of one member. by="orthants": candidates are the orthants' skylines around the member, from all points;
    by="blocks": those of blocks that no near point prunes."""
    index = index or build_index(points)
    rows = gathered(points, sets)
    if by == "blocks":
        return _refined(_candidates(index, rows, None, False), index, True)
    reached = rds_candidates(points, rows).join(F.broadcast(rows), "set_id").join(points, "id").select("set_id", "qs", "id", *coordinates(index.d))
    return _refined(reached, index, True)
