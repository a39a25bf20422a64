"""Inverse k-nearest-neighbour queries: the objects whose k-set, by (squared distance, id) and without themselves, holds all of Q."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine.functions.geometry import all_of, any_of, at, box_dominates, box_gap2, box_max_dist2, box_min_dist2, columns, coordinates, dist2, furthest, max_dist2_of_set, precedes, total
from inverse_engine.operators.common import chosen_member, gathered, intersected, iterated, singletons, without_queries
from inverse_engine.plans.blocks import TOP_BITS, Index, build_index, meeting, top_level
from inverse_engine.plans.store import stored
from inverse_engine.sources.points import dimension

#: Points of the blocks near Q that are read for pruners, as a multiple of k; points that prune, as a multiple of k, and over all sets
#: at most (they are broadcast).
PRUNERS, POINT_PRUNERS, MOST_POINT_PRUNERS = 2, 4, 400_000
#: Simplices of a hull at most, dimensions up to which hulls are used, tolerance inside them.
SIMPLICES, HULL_DIMENSIONS, INSIDE = 210, 5, 1e-9
#: Points that the definition looks at first, about.
FIRST_POINTS = 8_192
#: Side of the cells that candidates are refined together in, as a share of the unit.
BATCH_SIDE = 1 / 16


def _bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with the value worked out once: in a lambda of a list, a plain column would be worked out for every element."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def knn_reads(index: Index, probes: DataFrame, k: int) -> DataFrame:
    """(probe, cell, p_x..): the blocks that hold each probe's k-set, found from the larger cells down.

    The nearest boxes that hold k + 1 points bound the radius: first those of the top level, then blocks within that bound."""
    d = index.d
    p = probes.select(F.col("id").alias("probe"), *[F.col(c).alias(f"p_{c}") for c in coordinates(d)])
    y = columns(coordinates(d, "p_x"))

    def limit(boxes: DataFrame) -> DataFrame:
        """Adds limit: a distance within which the given boxes hold more than k points (the probe itself may be one), if they do."""
        far = box_max_dist2(at(F.col("lo"), d), at(F.col("hi"), d), y)
        upto = boxes.withColumn("far", far).withColumn("upto", F.sum("cnt").over(Window.partitionBy("probe").orderBy("far", "cell")))
        return upto.withColumn("limit", F.min(F.when(F.col("upto") > k, F.col("far"))).over(Window.partitionBy("probe")))

    top, _ = top_level(index, "cell")
    bound = limit(p.join(F.broadcast(top))).groupBy("probe", *[f"p_{c}" for c in coordinates(d)]).agg(F.first("limit").alias("most"))
    reached = meeting(index, bound, lambda lo, hi: F.col("most").isNull() | (box_min_dist2(lo, hi, y) <= F.col("most")))
    near = F.col("limit").isNull() | (box_min_dist2(at(F.col("lo"), d), at(F.col("hi"), d), y) <= F.col("limit"))
    return limit(reached).where(near).select("probe", "cell", *[f"p_{c}" for c in coordinates(d)])


def knn(points: DataFrame, probes: DataFrame, k: int, index: Index | None = None) -> DataFrame:
    """(probe, id, rank, d2): the k-set of each probe (id, x0..); a probe's own id does not count."""
    d = dimension(points)
    index = index or build_index(points)
    y = columns(coordinates(d, "p_x"))
    near = knn_reads(index, probes, k).join(index.points, "cell").where(F.col("probe") != F.col("id")).select("probe", "id", dist2(columns(coordinates(d)), y).alias("d2"))
    rank = F.row_number().over(Window.partitionBy("probe").orderBy("d2", "id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k)


def knn_validate(rows: DataFrame) -> DataFrame:
    """Adds alive: no more members than places."""
    return rows.withColumn("alive", F.col("m") <= F.col("k"))


def reduced_k(k: Column | int, m: Column | int) -> Column | int:
    """The k of a single member's reverse query among the points without the other members."""
    return k - m + 1


def convex_ring(x: np.ndarray) -> list[int]:
    """Places of the corners of the convex hull of points of two dimensions, around it: two monotone chains."""
    order = sorted(range(len(x)), key=lambda i: (x[i, 0], x[i, 1]))
    ring: list[int] = []
    for way in (order, order[::-1]):
        chain: list[int] = []
        for i in way:
            while len(chain) > 1 and np.cross(np.append(x[chain[-1]] - x[chain[-2]], 0), np.append(x[i] - x[chain[-2]], 0))[2] <= 0:
                chain.pop()
            chain.append(i)
        ring += chain[:-1]
    return ring


def simplices_of(x: np.ndarray, d: int) -> np.ndarray:
    """Affine maps, each of d + 1 rows of d + 1 numbers, of simplices of the members x; a point is inside one if all its barycentric
    coordinates exceed INSIDE. In one dimension an interval, in two the triangles of the convex polygon, above that at most SIMPLICES
    simplices of members. Missing ones (and what lies on their faces) only loosen the bounds."""
    maps: list[np.ndarray] = []
    corners = combinations(range(len(x)), d + 1)
    if d == 1:
        order = np.argsort(x[:, 0])
        corners = [(order[0], order[-1])]
    elif d == 2:
        ring = convex_ring(x)
        # Two fans: what lies on a diagonal of one is inside the other.
        corners = [(r[0], r[i], r[i + 1]) for r in (ring, ring[1:] + ring[:1]) for i in range(1, len(r) - 1)]
    for c in corners:
        if len(maps) >= SIMPLICES:
            break
        a = np.vstack([x[list(c)].T, np.ones(len(c))])
        if a.shape[0] == a.shape[1] and abs(np.linalg.det(a)) > 1e-12:
            maps.append(np.linalg.inv(a))
    return np.array(maps).reshape(len(maps), d + 1, d + 1)


def hulls(rows: DataFrame, d: int) -> DataFrame:
    """(set_id, simplices array<array<double>>): the maps of simplices_of, row after row."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        for set_id, qs in zip(frame["set_id"], frame["qs"], strict=True):
            x = np.array([list(q["x"]) for q in qs], dtype=np.float64).reshape(len(qs), -1)[:, :d]
            out.append((set_id, [a.ravel().tolist() for a in simplices_of(x, d)]))
        return pd.DataFrame(out, columns=["set_id", "simplices"])

    kind_of = rows.schema["set_id"].dataType
    if kind_of.typeName() == "struct":
        raise ValueError("hulls are of whole sets")
    return rows.select("set_id", "qs").groupBy("set_id").applyInPandas(build, f"set_id {kind_of.simpleString()}, simplices array<array<double>>")


def in_hull(p: list[Column], simplices: Column) -> Column:
    d = len(p)
    row = lambda s, r: total([F.get(s, F.lit(r * (d + 1) + i)) * x for i, x in enumerate(p)] + [F.get(s, F.lit(r * (d + 1) + d))])
    return F.exists(simplices, lambda s: all_of([row(s, r) > INSIDE for r in range(d + 1)]))


def inside_simplices(places: np.ndarray, simplices: np.ndarray) -> np.ndarray:
    """Of boxes or points, given by their corners (number, corners, d): do all corners lie in one simplex? So does every point then."""
    d = places.shape[2]
    found, left = np.zeros(len(places), dtype=bool), np.arange(len(places))
    for s in simplices:
        p = places[left]
        within = np.ones(len(left), dtype=bool)
        for row in s:  # summed in the order of in_hull
            held = row[0] * p[:, :, 0]
            for i in range(1, d):
                held = held + row[i] * p[:, :, i]
            within &= (held + row[d] > INSIDE).all(axis=1)
        found[left[within]] = True
        left = left[~within]
        if not len(left):
            break
    return found


def hull_members(points: DataFrame, rows: DataFrame, d: int) -> DataFrame:
    """(set_id, id): points inside the hull of Q that are not members and do not lie on one."""
    x = columns(coordinates(d))
    shaped = F.broadcast(rows.select("set_id", "qs").join(hulls(rows, d), "set_id"))
    apart = F.forall("qs", lambda q: (q["q"] != F.col("id")) & (dist2(x, at(q["x"], d)) > 0))
    ends = all_of([(x[i] >= F.array_min(F.transform("qs", lambda q: F.get(q["x"], F.lit(i))))) & (x[i] <= F.array_max(F.transform("qs", lambda q: F.get(q["x"], F.lit(i))))) for i in range(d)])
    return points.join(shaped, ends & in_hull(x, F.col("simplices")) & apart).select("set_id", "id")


def members_box(rows: DataFrame, d: int) -> DataFrame:
    """Adds q_lo, q_hi: the box of the members."""
    ends = lambda i, f: f(F.transform("qs", lambda q: F.get(q["x"], F.lit(i))))
    return rows.withColumn("q_lo", F.array(*[ends(i, F.array_min) for i in range(d)])).withColumn("q_hi", F.array(*[ends(i, F.array_max) for i in range(d)]))


def _apart(lo: list[Column], hi: list[Column], d: int) -> Column:
    """Is the box apart from the members' box, and so from the hull and all members?"""
    return any_of([(a > z) | (b < y) for a, b, y, z in zip(lo, hi, at(F.col("q_lo"), d), at(F.col("q_hi"), d), strict=True)])


def hull_counts(index: Index, rows: DataFrame) -> DataFrame:
    """(set_id, h): how many points the hull holds, members and their places aside. A block inside the hull without a member in its
    box counts unread; of the others that meet the members' box the points are read. The members reach the driver (they are broadcast
    everywhere else), their simplices are worked out where they are used."""
    d = index.d
    names, kind_of = coordinates(d), rows.schema["set_id"].dataType
    if kind_of.typeName() == "struct":
        raise ValueError("hulls are of whole sets")
    members = {r["set_id"]: (np.array([q["q"] for q in r["qs"]]), np.array([q["x"][:d] for q in r["qs"]], dtype=np.float64).reshape(-1, d)) for r in rows.select("set_id", "qs").collect()}
    boxed = F.broadcast(members_box(rows.select("set_id", "qs"), d).select("set_id", "q_lo", "q_hi"))
    lo, hi = at(F.col("lo"), d), at(F.col("hi"), d)
    met = index.blocks.join(boxed, ~_apart(lo, hi, d)).select("set_id", "cell", "cnt", "lo", "hi")

    def by_set(frames: Iterator[pd.DataFrame], test: Callable[[pd.DataFrame, np.ndarray, np.ndarray, np.ndarray], np.ndarray]) -> Iterator[tuple[pd.DataFrame, np.ndarray]]:
        shapes: dict[object, np.ndarray] = {}
        for frame in frames:
            passed = np.zeros(len(frame), dtype=bool)
            for set_id, place in frame.groupby("set_id", sort=False).indices.items():
                q, x = members[set_id]
                if set_id not in shapes:
                    shapes[set_id] = simplices_of(x, d)
                passed[place] = test(frame.iloc[place], q, x, shapes[set_id])
            yield frame, passed

    def covered(part: pd.DataFrame, q: np.ndarray, x: np.ndarray, simplices: np.ndarray) -> np.ndarray:
        ends = [np.array(part[c].tolist(), dtype=np.float64).reshape(-1, d) for c in ("lo", "hi")]
        holds = ((ends[0][:, None] <= x[None]) & (x[None] <= ends[1][:, None])).all(axis=2).any(axis=1)
        corners = np.stack([np.stack([ends[mask >> i & 1][:, i] for i in range(d)], axis=1) for mask in range(1 << d)], axis=1)
        return inside_simplices(corners, simplices) & ~holds

    def held(part: pd.DataFrame, q: np.ndarray, x: np.ndarray, simplices: np.ndarray) -> np.ndarray:
        places = part[names].to_numpy(dtype=np.float64)
        apart = ~np.isin(part["id"].to_numpy(), q)
        for member in x:
            apart &= (places != member).any(axis=1)
        return apart & inside_simplices(places[:, None], simplices)

    def blocks(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame, passed in by_set(frames, covered):
            yield frame[["set_id", "cell", "cnt"]].assign(inside=passed)

    def objects(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame, passed in by_set(frames, held):
            yield frame[passed][["set_id"]]

    met = stored(met.mapInPandas(blocks, f"set_id {kind_of.simpleString()}, cell bigint, cnt bigint, inside boolean"), "knn-hull-blocks")
    whole = met.where("inside").groupBy("set_id").agg(F.sum("cnt").alias("h"))
    part = met.where(~F.col("inside")).select("set_id", "cell")
    near = index.read(part).join(F.broadcast(part), "cell").select("set_id", "id", *names)
    read = near.mapInPandas(objects, f"set_id {kind_of.simpleString()}").groupBy("set_id").agg(F.count("*").alias("h"))
    return whole.unionByName(read).groupBy("set_id").agg(F.sum("h").alias("h"))


def hull_bound(k: Column | int, h: Column | int, m: Column | int, inside: bool) -> Column | int:
    """How many objects outside hull and Q may be nearer than the furthest member."""
    return k - h - m + int(inside)


def _nearest_blocks(index: Index, rows: DataFrame) -> DataFrame:
    """(set_id, p_cell, p_lo, p_hi, p_cnt): blocks by their largest distance to Q, up to PRUNERS * POINT_PRUNERS * k + m points of each set."""
    d = index.d
    lo, hi = at(F.col("lo"), d), at(F.col("hi"), d)
    far = F.array_max(F.transform("qs", lambda q: box_max_dist2(lo, hi, at(q["x"], d))))
    order = F.sum("cnt").over(Window.partitionBy("set_id").orderBy("far", "cell"))
    # Only blocks that begin within the largest distance of the nearest ones can be among them.
    top, _ = top_level(index, "cell")
    some = top.join(F.broadcast(rows)).withColumn("far", far).withColumn("upto", order).where(F.col("upto") - F.col("cnt") <= PRUNERS * POINT_PRUNERS * F.col("k") + F.col("m"))
    reach = some.groupBy("set_id").agg(F.max("far").alias("reach"))
    asked = rows.select("set_id", "k", "m", "qs").join(F.broadcast(reach), "set_id")
    near = meeting(index, asked, lambda a, b: F.array_max(F.transform("qs", lambda q: box_min_dist2(a, b, at(q["x"], d)))) <= F.col("reach"))
    ranked = near.withColumn("far", far).withColumn("upto", order).where(F.col("upto") - F.col("cnt") <= PRUNERS * POINT_PRUNERS * F.col("k") + F.col("m"))
    return ranked.select("set_id", F.col("cell").alias("p_cell"), F.col("lo").alias("p_lo"), F.col("hi").alias("p_hi"), F.col("cnt").alias("p_cnt"))


def point_pruners(index: Index, rows: DataFrame) -> DataFrame:
    """(set_id, near): the points nearest to all of Q, by their largest distance, POINT_PRUNERS * k of them, or as many as
    MOST_POINT_PRUNERS leaves to each set."""
    d = index.d
    x = columns(coordinates(d))
    share = max(1, MOST_POINT_PRUNERS // max(1, rows.count()))
    blocks = _nearest_blocks(index, rows).select("set_id", F.col("p_cell").alias("cell"))
    near = index.read(blocks).join(F.broadcast(blocks), "cell").join(F.broadcast(rows.select("set_id", "k", "qs")), "set_id")
    far = near.select("set_id", "k", "id", F.array(*x).alias("x"), max_dist2_of_set(x, F.col("qs"), d).alias("far"))
    rank = F.row_number().over(Window.partitionBy("set_id").orderBy("far", "id"))
    kept = far.withColumn("r", rank).where(F.col("r") <= F.least(F.col("k") * POINT_PRUNERS, F.lit(share)))
    return kept.groupBy("set_id").agg(F.collect_list(F.struct("id", "x")).alias("near"))


def _numbered(armed: DataFrame) -> DataFrame:
    """armed with a number of each set, `set_no`,, fixed as it is written."""
    return armed if "set_no" in armed.columns else stored(armed.withColumn("set_no", F.monotonically_increasing_id()), "knn-numbered-sets")


def _arrays(armed: DataFrame, d: int) -> dict[int, dict]:
    """By number of a set: k, m, h, its members (q, x), their box, and the points near Q (near_q, near_x). They reach the driver and all
    tasks, as what is broadcast does: at most MOST_POINT_PRUNERS points, and the members."""
    out = {r["set_no"]: {"k": r["k"], "m": r["m"], "h": r["h"], "lo": np.array(r["q_lo"]), "hi": np.array(r["q_hi"])} for r in armed.select("set_no", "k", "m", "h", "q_lo", "q_hi").collect()}
    for column, q, x in (("qs", "q", "x"), ("near", "near_q", "near_x")):
        key = "q" if column == "qs" else "id"
        flat = armed.select("set_no", F.explode(column).alias("p")).select("set_no", F.col(f"p.{key}").alias("q"), *[F.get("p.x", F.lit(j)).alias(f"x{j}") for j in range(d)]).toArrow()
        owner, ids = flat["set_no"].to_numpy(), flat["q"].to_numpy()
        places = np.stack([flat[f"x{j}"].to_numpy() for j in range(d)], axis=1) if len(ids) else np.zeros((0, d))
        order = np.argsort(owner, kind="stable")
        starts = np.searchsorted(owner[order], list(out), side="left"), np.searchsorted(owner[order], list(out), side="right")
        for i, start, end in zip(out, *starts, strict=True):
            out[i][q], out[i][x] = ids[order[start:end]], places[order[start:end]]
    return out


def _squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of all a to all b, summed by ascending dimension as dist2 does."""
    out = np.zeros((len(a), len(b)))
    for j in range(a.shape[1]):
        out += (a[:, None, j] - b[None, :, j]) ** 2
    return out


def _outside(x: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    return ((x < lo) | (x > hi)).any(axis=-1)


#: Objects or boxes that are compared with a set's near points at once.
STEP = 2_048


def _few_ahead(near: DataFrame, armed: DataFrame, d: int, mono: bool, hull: bool) -> DataFrame:
    """Of near (set_no, id, x..), those that the points near Q do not rule out."""
    sets, names = _arrays(armed, d), coordinates(d)

    def left(one: dict, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        # The furthest other member, by (squared distance, id): members by ascending id, so that the last greatest one counts.
        order = np.argsort(one["q"], kind="stable")
        q = one["q"][order]
        far = _squares(x, one["x"][order])
        if mono:
            far[ids[:, None] == q[None]] = -1.0
        last = len(q) - 1 - np.argmax(far[:, ::-1], axis=1)
        r2, rq = far[np.arange(len(x)), last][:, None], q[last][:, None]
        d2, near_q = _squares(x, one["near_x"]), one["near_q"][None]
        won = (d2 < r2) | ((d2 == r2) & (near_q < rq))
        if mono:
            won &= near_q != ids[:, None]
        kept = won.sum(axis=1) < one["k"]
        if hull:
            most = hull_bound(one["k"], one["h"], one["m"], True) - _outside(x, one["lo"], one["hi"]).astype(int)
            kept &= (won & _outside(one["near_x"], one["lo"], one["hi"])[None]).sum(axis=1) <= most
        return kept

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            kept = np.zeros(len(frame), dtype=bool)
            ids, x = frame["id"].to_numpy(), frame[names].to_numpy(dtype=np.float64)
            for i, all_ in frame.groupby("set_no", sort=False).indices.items():
                for start in range(0, len(all_), STEP):
                    place = all_[start : start + STEP]
                    kept[place] = left(sets[i], ids[place], x[place])
            yield frame[kept]

    near = near.select("set_no", "id", *[c for c in near.columns if c == "cell"], *names)
    return near.mapInPandas(run, near.schema)


def _referred(reached: DataFrame, d: int, include_query_objects: bool, mono: bool) -> DataFrame:
    """Candidates with ref, their furthest member (themselves aside), and places: how many others may precede it."""
    own = F.exists("qs", lambda q: q["q"] == F.col("id")) if mono else F.lit(False)
    others = F.filter("qs", lambda q: q["q"] != F.col("id")) if mono else F.col("qs")
    ref = reached.withColumn("own", own).where(F.lit(include_query_objects) | ~F.col("own")).withColumn("others", others).where(F.size("others") > 0)
    return ref.withColumn("ref", furthest(columns(coordinates(d)), F.col("others"), d)).withColumn("places", F.col("k") - F.col("own").cast("int") - 1)


def _uncrowded(reached: DataFrame, index: Index, include_query_objects: bool, mono: bool) -> DataFrame:
    """Candidates, stored, without those that too many points of their own block precede: the nearest points rule out most, and all of
    a crowded place, so that few are left to look for the blocks within their ball. Candidates of one place are tested once, against
    the places of the block and how many points each has; ties do not count, so that it is a lower bound."""
    d, names = index.d, coordinates(index.d)
    reached = stored(reached, "knn-candidates")
    if "cell" not in reached.columns or not reached.head(1):
        return reached
    x, y = columns(names), columns(coordinates(d, "c_x"))
    each = _referred(reached, d, include_query_objects, mono).select("cell", "set_id", F.col("id").alias("c"), F.col("ref.d2").alias("r2"), "places", *[F.col(n).alias(f"c_{n}") for n in names])
    asked = each.groupBy("cell", "set_id", "r2", "places", *y).agg(F.collect_list("c").alias("all"))
    near = index.read(reached.select("cell")).groupBy("cell", *x).agg(F.count("*").alias("cnt"))
    ahead = asked.join(near, "cell").where(dist2(x, y) < F.col("r2")).groupBy("cell", "set_id", "r2", "places", *y).agg(F.sum("cnt").alias("n"))
    # A candidate is itself among the points.
    crowded = ahead.where(F.col("n") - int(mono) > F.col("places")).select("cell", "set_id", "r2", "places", *y)
    lost = asked.join(crowded, ["cell", "set_id", "r2", "places", *[f"c_{n}" for n in names]]).select("set_id", F.explode("all").alias("id"))
    return stored(reached.join(lost, ["set_id", "id"], "left_anti"), "knn-uncrowded")


def _refinement_reads(reached: DataFrame, index: Index, include_query_objects: bool, mono: bool) -> tuple[DataFrame, DataFrame]:
    """For candidates (set_id, k, m, qs, id, x..): (set_id, c, covered, places) with the points of blocks that count unread, and
    (set_id, c, cell, r2, rq, c_x..), the blocks that must be read, of candidates that those leave open.

    Candidates of one cell of side BATCH_SIDE look for their blocks together."""
    d = index.d
    x = columns(coordinates(d))
    ref = _referred(reached, d, include_query_objects, mono)
    batch = F.hash(*[F.floor(c / BATCH_SIDE) for c in x])
    probe = ref.select("set_id", F.col("id").alias("c"), F.col("ref.d2").alias("r2"), F.col("ref.q").alias("rq"), "places", batch.alias("batch"), *[F.col(n).alias(f"c_{n}") for n in coordinates(d)])
    y = columns(coordinates(d, "c_x"))
    sides = [F.array(*[f(c) for c in y]).alias(n) for n, f in (("b_lo", F.min), ("b_hi", F.max))]
    batches = probe.groupBy("set_id", "batch").agg(*sides, F.max("r2").alias("r2"))
    b_lo, b_hi = at(F.col("b_lo"), d), at(F.col("b_hi"), d)
    # The gap of boxes is summed in another order than a point's distance: a little more is let through.
    hit = meeting(index, batches, lambda lo, hi: box_gap2(b_lo, b_hi, lo, hi) <= F.col("r2") * (1 + 1e-9) + 1e-300).select("set_id", "batch", "cell", "lo", "hi", "cnt")
    lo, hi = at(F.col("lo"), d), at(F.col("hi"), d)
    near, far = box_min_dist2(lo, hi, y), box_max_dist2(lo, hi, y)
    # Blocks wholly within the ball count unread; an object's own block is never among them, as its reading settles ties and itself.
    hit = probe.join(hit, ["set_id", "batch"]).where(near <= F.col("r2")).withColumn("whole", (far < F.col("r2")) & ~(all_of([(a >= l) & (a <= h) for a, l, h in zip(y, lo, hi, strict=True)])))
    covered = hit.groupBy("set_id", "c").agg(F.sum(F.when(F.col("whole"), F.col("cnt")).otherwise(F.lit(0))).alias("covered"), F.first("places").alias("places"))
    open_ = covered.where(F.col("covered") <= F.col("places"))
    part = hit.where(~F.col("whole")).select("set_id", "c", "r2", "rq", "cell", *[f"c_{n}" for n in coordinates(d)]).join(open_.select("set_id", "c"), ["set_id", "c"], "left_semi")
    return open_, part


def _accepted(reached: DataFrame, index: Index, include_query_objects: bool, mono: bool = True) -> DataFrame:
    """(set_id, id) of candidates (set_id, k, m, qs, id, x..) of which at most k - 1 others precede the furthest member."""
    d = index.d
    reached = _uncrowded(reached, index, include_query_objects, mono)
    open_, part = _refinement_reads(reached, index, include_query_objects, mono)
    x, y = columns(coordinates(d)), columns(coordinates(d, "c_x"))
    same = (F.col("id") != F.col("c")) if mono else F.lit(True)
    ahead = precedes(dist2(x, y), F.col("id"), F.col("r2"), F.col("rq"))
    counted = part.join(index.points, "cell").where(same & ahead).groupBy("set_id", "c").agg(F.count("*").alias("n"))
    done = open_.join(counted, ["set_id", "c"], "left").where(F.col("covered") + F.coalesce("n", F.lit(0)) <= F.col("places"))
    return done.select("set_id", F.col("c").alias("id"))


def prune_counters(entries: DataFrame, armed: DataFrame, d: int) -> DataFrame:
    """(set_id, k, m, h, cell, counter, beyond, apart) for entries (cell, lo, hi, and set_id or not): how many of the points near Q are
    nearer than Q's furthest member to every place of the entry's box, all of them (counter) and those apart from the members' box
    (beyond); whether the entry itself is apart from that box. Both are lower bounds of what an object in the entry has ahead."""
    armed = _numbered(armed)
    sets = _arrays(armed, d)

    def counted(one: dict, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        # Any member will do; the one that is furthest from the box's middle prunes most.
        q = one["x"][np.argmax(_squares((lo + hi) / 2, one["x"]), axis=1)]
        p = one["near_x"]
        total_, outside = np.zeros((len(lo), len(p))), np.zeros((len(lo), len(p)), dtype=bool)
        for j in range(d):
            ends = [(e[:, None] - p[None, :, j]) ** 2 - ((e - q[:, j]) ** 2)[:, None] for e in (lo[:, j], hi[:, j])]
            total_ += np.maximum(*ends)
            outside |= (p[None, :, j] < lo[:, None, j]) | (p[None, :, j] > hi[:, None, j])
        won = outside & (total_ < 0)
        apart = ((lo > one["hi"]) | (hi < one["lo"])).any(axis=1)
        return won.sum(axis=1), (won & _outside(p, one["lo"], one["hi"])[None]).sum(axis=1), apart

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            lo, hi = [np.array(frame[c].tolist(), dtype=np.float64).reshape(-1, d) for c in ("lo", "hi")]
            cells = frame["cell"].to_numpy()
            asked = frame.groupby("set_no", sort=False).indices if "set_no" in frame else dict.fromkeys(sets, np.arange(len(frame)))
            for i, all_ in asked.items():
                for start in range(0, len(all_), STEP):
                    place = all_[start : start + STEP]
                    counter, beyond, apart = counted(sets[i], lo[place], hi[place])
                    yield pd.DataFrame({"set_no": i, "cell": cells[place], "counter": counter, "beyond": beyond, "apart": apart})

    own = F.broadcast(armed.select("set_no", "set_id", "k", "m", "h"))
    if "set_id" in entries.columns:
        asked = entries.join(F.broadcast(armed.select("set_no", "set_id")), "set_id").select("set_no", "cell", "lo", "hi")
    else:
        asked = entries.select("cell", "lo", "hi")
    asked = asked.repartition(max(1, entries.sparkSession.sparkContext.defaultParallelism))
    counts = asked.mapInPandas(run, "set_no bigint, cell bigint, counter int, beyond int, apart boolean")
    return counts.join(own, "set_no").select("set_id", "k", "m", "h", "cell", "counter", "beyond", "apart")


def alive_blocks(index: Index, rows: DataFrame, hull: bool, include_query_objects: bool = False) -> tuple[DataFrame, DataFrame]:
    """(set_id, cell) of the blocks that no counter removes, and the rows of sets that may have results, with `near` (the points that
    prune), the members' box, and h (null where the hull's bounds are not used: where members may be results, or in many dimensions).

    From the top level down: blocks of larger cells that are pruned are not looked at. Exactness is left to refinement."""
    use = hull and index.d <= HULL_DIMENSIONS and not include_query_objects
    rows = members_box(rows, index.d)
    if use:
        # Outside the hull at most k - h - m others may be nearer, inside one more: below zero nobody is left.
        rows = rows.join(F.broadcast(hull_counts(index, rows)), "set_id", "left").withColumn("h", F.coalesce("h", F.lit(0)))
        rows = rows.where(hull_bound(F.col("k"), F.col("h"), F.col("m"), True) >= 0)
    else:
        rows = rows.withColumn("h", F.lit(None).cast("long"))
    rows = stored(rows, "knn-live-sets")
    armed = rows.join(F.broadcast(point_pruners(index, rows)), "set_id", "left")
    armed = _numbered(armed.withColumn("near", F.coalesce("near", F.array().cast("array<struct<id:bigint,x:array<double>>>"))))

    def left(entries: DataFrame) -> DataFrame:
        counted = prune_counters(entries, armed, index.d).where(F.col("counter") < F.col("k"))
        if use:
            counted = counted.where(F.col("beyond") <= hull_bound(F.col("k"), F.col("h"), F.col("m"), True) - F.col("apart").cast("int"))
        return counted.select("set_id", "cell")

    if index.n_blocks <= 1 << TOP_BITS:
        return stored(left(index.blocks), "knn-alive-blocks"), armed
    top, shift = top_level(index, "cell")
    above = stored(left(top), "knn-alive-cells").withColumnRenamed("cell", "up")
    below = index.blocks.withColumn("up", F.shiftright("cell", shift)).join(above, "up").drop("up")
    return stored(left(below), "knn-alive-blocks"), armed


def _candidates(index: Index, rows: DataFrame, pool: DataFrame | None, hull: bool, include_query_objects: bool, prune_blocks: bool = True, prune_points: bool = True) -> DataFrame:
    """(set_id, k, m, qs, id, x.., and cell where they are the index's points) that no filter removes."""
    d = index.d
    names = coordinates(d)
    use = pool is None and hull and d <= HULL_DIMENSIONS and not include_query_objects
    alive, armed = alive_blocks(index, rows, use, include_query_objects)
    numbers = F.broadcast(armed.select("set_no", "set_id"))
    if pool is not None:
        near = pool.join(numbers)
    elif prune_blocks:
        near = index.read(alive).join(alive.join(numbers, "set_id").select("cell", "set_no"), "cell")
    else:
        near = index.points.join(numbers)
    near = near.select("set_no", "id", *([] if pool is not None else ["cell"]), *names)
    if prune_points:
        near = _few_ahead(near, armed, d, pool is None, use)
    return near.join(F.broadcast(armed.select("set_no", "set_id", "k", "m", "qs")), "set_no").select("set_id", "k", "m", "qs", *near.columns[1:])


def inverse_knn(points: DataFrame, sets: DataFrame, k: int | None = None, strategy: str = "joint", include_query_objects: bool = False, candidates: DataFrame | None = None, index: Index | None = None, hull: bool = True, refine: str = "range_count", seed: int = 0, prune_blocks: bool = True, prune_points: bool = True) -> DataFrame:
    """(set_id, id). `sets` may hold a column k; candidates: objects of another table, of which none is a point.

    hull, prune_blocks, prune_points: filters of the joint method that can be left out; results are the same."""
    d = dimension(points)
    rows = gathered(points, sets)
    if k is not None:
        rows = rows.withColumn("k", F.lit(int(k)))
    rows = knn_validate(rows).where("alive").drop("alive")
    mono = candidates is None
    if strategy == "brute":
        return _brute(points, rows, d, include_query_objects, candidates)
    index = index or build_index(points)
    if strategy == "joint":
        reached = _candidates(index, rows, candidates, hull, include_query_objects, prune_blocks, prune_points)
        if refine == "search":
            return _searched(reached, points, index, d, include_query_objects)
        return _accepted(reached, index, include_query_objects, mono)
    reverse = lambda one: _accepted(_candidates(index, one, candidates, False, False), index, False, mono)
    if strategy == "naive":
        # A member is no result, but it is a point of the other members' queries.
        return without_queries(iterated(rows, reverse), rows) if mono else iterated(rows, reverse)
    if strategy == "naive_at_once":
        each = reverse(singletons(rows))
        owners = F.broadcast(rows.select(F.col("set_id").alias("w"), F.col("m").alias("owner_m")))
        return intersected(each.join(owners, F.col("set_id.owner") == F.col("w")).select(F.col("set_id.owner").alias("owner"), "owner_m", "id"))
    if strategy == "single":
        reached = reverse(chosen_member(rows, seed).drop("all_qs", "all_m"))
        pool = points if mono else candidates
        back = reached.join(F.broadcast(rows), "set_id").join(pool, "id").select("set_id", "k", "m", "qs", "id", *coordinates(d))
        return _searched(back, points, index, d, False) if mono else _accepted(back, index, False, False)
    raise ValueError(strategy)


def reduced_k_candidates(points: DataFrame, sets: DataFrame, k: int, index: Index | None = None) -> DataFrame:
    """(set_id, id): the objects that pass, for every single member, its reverse query by the reduced k among the points without the
    other members.

    The index holds the other members too: of an object's points ahead, those among them are known from the set, and the object may
    have as many more. At most all m - 1 others are, so that the filters by k leave every object that passes."""
    d = dimension(points)
    x = columns(coordinates(d))
    rows = gathered(points, sets)
    index = index or build_index(points)
    own = rows.select(F.col("set_id").alias("owner"), F.col("qs").alias("all"))
    reached = _candidates(index, singletons(rows).withColumn("k", F.lit(int(k))), None, False, False)
    reached = reached.withColumn("owner", F.col("set_id.owner")).join(F.broadcast(own), "owner").where(~F.exists("all", lambda z: z["q"] == F.col("id")))
    q, q2 = F.get("qs.q", F.lit(0)), dist2(x, at(F.get("qs.x", F.lit(0)), d))
    ahead = F.size(F.filter("all", lambda z: (z["q"] != q) & precedes(dist2(x, at(z["x"], d)), z["q"], q2, q)))
    passed = _accepted(reached.withColumn("k", reduced_k(F.lit(int(k)), F.size("all")) + ahead), index, False)
    owners = F.broadcast(rows.select(F.col("set_id").alias("w"), F.col("m").alias("owner_m")))
    return intersected(passed.join(owners, F.col("set_id.owner") == F.col("w")).select(F.col("set_id.owner").alias("owner"), "owner_m", "id"))


def _searched(reached: DataFrame, points: DataFrame, index: Index, d: int, include_query_objects: bool) -> DataFrame:
    """Refinement by k-nearest-neighbour searches: a candidate's k-set must hold all of Q (itself aside, if it is a member)."""
    own = F.exists("qs", lambda q: q["q"] == F.col("id"))
    asked = reached.where(F.lit(include_query_objects) | ~own)
    most = asked.agg(F.max("k")).first()[0]
    if most is None:
        return asked.select("set_id", "id")
    near = knn(points, asked.select("id", *coordinates(d)).distinct(), most, index).select("probe", F.col("id").alias("n"), "rank")
    wanted = asked.select("set_id", "k", F.col("id").alias("probe"), F.explode("qs.q").alias("n")).where(F.col("n") != F.col("probe"))
    size = wanted.groupBy("set_id", "probe").agg(F.count("*").alias("want"), F.first("k").alias("k"), F.first("probe").alias("p"))
    held = wanted.join(near, ["probe", "n"]).where(F.col("rank") <= F.col("k") - F.lit(0)).groupBy("set_id", "probe").agg(F.count("*").alias("have"), F.max("rank").alias("last"))
    members = reached.where(own).select("set_id", F.col("id").alias("probe"), F.lit(1).alias("taken"))
    done = size.join(held, ["set_id", "probe"]).join(members, ["set_id", "probe"], "left").where((F.col("want") == F.col("have")) & (F.col("last") <= F.col("k") - F.coalesce("taken", F.lit(0))))
    return done.select("set_id", F.col("probe").alias("id"))


def _not_ruled_out(asked: DataFrame, points: DataFrame, d: int, mono: bool) -> DataFrame:
    """asked without the objects that have k of FIRST_POINTS points ahead of their furthest member: whatever the other points are,
    they are no results. All that are left meet every point; the points looked at first decide how many those are, not which."""
    first = points.where(F.pmod(F.xxhash64("id"), F.lit(max(1, points.count() // FIRST_POINTS))) == 0).limit(2 * FIRST_POINTS).toPandas()
    ids, places = first["id"].to_numpy(), [first[n].to_numpy() for n in coordinates(d)]
    names, step = coordinates(d, "c_x"), 1024

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            own, most = [frame[n].to_numpy() for n in names], (frame["k"] - frame["own"].astype(int)).to_numpy()
            c, r2, ahead = frame["c"].to_numpy(), frame["r2"].to_numpy(), np.zeros(len(frame), dtype=np.int64)
            left = np.arange(len(frame))
            for i in range(0, len(ids), step):
                d2 = 0.0
                for x, y in zip(places, own, strict=True):
                    d2 = d2 + (x[None, i : i + step] - y[left, None]) ** 2
                won = d2 < r2[left, None]
                if mono:
                    won &= ids[None, i : i + step] != c[left, None]
                ahead[left] += won.sum(axis=1)
                left = left[ahead[left] < most[left]]
            yield frame.iloc[left]

    return stored(asked.mapInPandas(run, asked.schema), "knn-not-ruled-out")


def _brute(points: DataFrame, rows: DataFrame, d: int, include_query_objects: bool, candidates: DataFrame | None) -> DataFrame:
    """The definition: every object against every point."""
    mono = candidates is None
    pool = (points if mono else candidates).select(F.col("id").alias("c"), *[F.col(n).alias(f"c_{n}") for n in coordinates(d)])
    y, x = columns(coordinates(d, "c_x")), columns(coordinates(d))
    own = F.exists("qs", lambda q: q["q"] == F.col("c")) if mono else F.lit(False)
    asked = pool.join(F.broadcast(rows)).withColumn("own", own).where(F.lit(include_query_objects) | ~F.col("own")).withColumn("others", F.filter("qs", lambda q: q["q"] != F.col("c")) if mono else F.col("qs")).where(F.size("others") > 0)
    asked = asked.withColumn("ref", furthest(y, F.col("others"), d))
    asked = _not_ruled_out(asked.select("set_id", "c", "k", "own", F.col("ref.d2").alias("r2"), F.col("ref.q").alias("rq"), *y), points, d, mono)
    ahead = precedes(dist2(x, y), F.col("id"), F.col("r2"), F.col("rq"))
    counted = asked.join(points, (F.col("id") != F.col("c")) & ahead if mono else ahead, "left").groupBy("set_id", "c", "k", "own").agg(F.count("id").alias("n"))
    return counted.where(F.col("n") <= F.col("k") - F.col("own").cast("int") - 1).select("set_id", F.col("c").alias("id"))


__all__ = ["hull_bound", "hull_counts", "hull_members", "inverse_knn", "knn", "prune_counters", "reduced_k", "reduced_k_candidates"]
