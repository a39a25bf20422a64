"""Steps that make the queries fit larger tables give what the plain definitions give."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import coordinates
from inverse_engine.operators import knn
from inverse_engine.operators.common import gathered
from inverse_engine.operators.framework import EpsRange
from inverse_engine.plans.accesses import requests
from inverse_engine.plans.blocks import build_index
from inverse_engine.plans.store import stored
from inverse_engine.sources.points import synthetic
from inverse_engine.sources.query_sets import sample_query_sets


@pytest.fixture(scope="module")
def cloud(spark):
    return stored(synthetic(spark, 6000, 3, clusters=3, seed=5), "test-points")


def test_hull_counts_of_ten_members_in_three_dimensions(spark, cloud):
    rows = gathered(cloud, sample_query_sets(cloud, 3, 10, 0.02))
    index = build_index(cloud, 64)
    got = {r["set_id"]: r["h"] for r in knn.hull_counts(index, rows).collect()}
    held = {r["set_id"]: r["n"] for r in knn.hull_members(cloud, rows, 3).groupBy("set_id").count().withColumnRenamed("count", "n").collect()}
    assert got == held and sum(got.values()) > 0
    # The folders of a small index are few: opening their files took longer than all else.
    assert index.points.select("zone").distinct().count() <= 1


def test_reduced_k_of_each_member_among_the_points_without_the_others(spark, cloud):
    points = cloud.where("id < 900")
    sets = sample_query_sets(points, 3, 4, 0.05)
    got = {(r["set_id"], r["id"]) for r in knn.reduced_k_candidates(points, sets, 200, build_index(points, 32)).collect()}
    frame = points.toPandas()
    ids, x = frame["id"].to_numpy(), frame[coordinates(3)].to_numpy()
    members = {}
    for r in sets.collect():
        members.setdefault(r["set_id"], []).append(r["q_id"])
    wanted = set()
    for set_id, qs in members.items():
        free = ~np.isin(ids, qs)
        for c in np.flatnonzero(free):
            d2 = sum((x[:, i] - x[c, i]) ** 2 for i in range(3))
            places = {q: d2[ids == q][0] for q in qs}
            ahead = [sum(free & (ids != ids[c]) & ((d2 < z) | ((d2 == z) & (ids < q)))) for q, z in places.items()]
            if max(ahead) < 200 - len(qs) + 1:
                wanted.add((set_id, ids[c]))
    assert got == wanted and wanted


@pytest.mark.parametrize("method", ["joint", "naive", "single"])
def test_page_accesses_of_the_range_query_are_those_of_the_definition(spark, cloud, method):
    points = cloud.where("id < 1500")
    points = stored(points.unionByName(points.where("id < 500").withColumn("id", F.col("id") + 10_000)), "test-copies")  # places with copies
    index = build_index(points, 16)
    drawn = sample_query_sets(points, 4, 5, 0.02, ranked=True)
    assert drawn.where("r <= 3").drop("r").exceptAll(sample_query_sets(points, 4, 3, 0.02)).count() == 0
    eps, sets = 0.15, drawn.drop("r")
    frame, blocks = points.toPandas(), index.blocks.collect()
    ids, x = frame["id"].to_numpy(), frame[coordinates(3)].to_numpy()
    lo, hi = np.array([b["lo"] for b in blocks]), np.array([b["hi"] for b in blocks])
    near = lambda q: (np.maximum(np.maximum(lo - q, q - hi), 0) ** 2).sum(axis=1) <= eps * eps
    within = lambda q: ((x - q) ** 2).sum(axis=1) <= eps * eps
    wanted = {}
    for row in gathered(points, sets).select("*", chosen_order().alias("chosen")).collect():
        q = {m["q"]: np.array(m["x"]) for m in row["qs"]}
        if method == "joint":
            apart = max(((a - b) ** 2).sum() for a in q.values() for b in q.values()) > 4 * eps * eps
            window = (hi >= np.max(list(q.values()), axis=0) - eps).all(axis=1) & (lo <= np.min(list(q.values()), axis=0) + eps).all(axis=1)
            times = (np.all([near(p) for p in q.values()], axis=0) & window & (not apart)).astype(int)
        elif method == "naive":
            times, left = np.zeros(len(blocks), dtype=int), np.ones(len(ids), dtype=bool)
            for p in q.values():
                if left.any():
                    times, left = times + near(p), left & within(p)
        else:
            found = within(q[row["chosen"]]) & ~np.isin(ids, list(q))
            times = near(q[row["chosen"]]) + sum((near(p).astype(int) for p in x[found]), np.zeros(len(blocks), dtype=int))
        wanted |= {(row["set_id"], b["cell"]): int(n) for b, n in zip(blocks, times, strict=True) if n}
    got = {(r["set_id"], r["cell"]): r["count"] for r in requests(index, sets, EpsRange(eps), method).groupBy("set_id", "cell").count().collect()}
    assert got == wanted and wanted


def chosen_order():
    return F.array_min(F.transform("qs", lambda q: F.struct(F.xxhash64(q["q"], F.lit(0)).alias("h"), q["q"].alias("q"))))["q"]


def test_index_summary_stands_for_all_rows(spark, monkeypatch):
    import numpy as np

    from inverse_engine.plans import blocks

    monkeypatch.setattr(blocks, "CHUNK", 1_000)  # a session's own workers get the value with the function
    rows = spark.range(0, 20_000, 1, 3).selectExpr("id", "pow(id / 20000D, 3) AS x0", "CAST(id % 7 AS DOUBLE) AS x1")
    merged, some = blocks.summary(rows, 2, 200)
    assert [round(w.sum()) for _, w in merged] == [20_000, 20_000] and len(some[0]) == len(some[1]) < 20_000
    v, w = merged[0]
    assert abs(v[np.searchsorted(np.cumsum(w), 10_000)] - 0.125) < 0.01
    index = blocks.build_index(rows, 100)
    assert index.points.count() == 20_000 and index.blocks.agg({"cnt": "sum"}).first()[0] == 20_000
    assert index.points.where("zone != shiftright(cell, %d)" % index.zone_shift).count() == 0


def test_cents_round_as_decimal_digits_do(spark):
    from pyspark.sql import functions as F

    from inverse_engine.sources.points import _cents

    rows = spark.createDataFrame([(x,) for x in (0.0, 0.005, -0.005, 1.005, 2.675, -2.675, 0.0049999999999999994, 123456.78, -0.01, 4.5e13, 9e15, None)], "v double")
    assert rows.where(~_cents("v").eqNullSafe(F.round(F.col("v") * 100).cast("long"))).count() == 0


def test_candidates_of_a_crowded_place_go_before_balls_are_looked_up(spark):
    once = stored(synthetic(spark, 300, 2, seed=9), "test-once")
    points = stored(once.join(spark.range(6).withColumnRenamed("id", "r")).selectExpr("id * 6 + r AS id", "x0", "x1"), "test-copies")
    index = build_index(points, 64)
    rows = gathered(points, sample_query_sets(points, 2, 3, 0.01)).withColumn("k", F.lit(5))
    assert gathered(points, rows) is rows
    reached = stored(knn._candidates(index, rows, None, False, False), "test-candidates")
    left = knn._uncrowded(reached, index, False, True)
    # Five copies are ahead of any member elsewhere, which is one more than places.
    assert left.count() < reached.count()
    got = {tuple(r) for r in knn._accepted(reached, index, False).collect()}
    assert got == {tuple(r) for r in knn.inverse_knn(points, rows, 5, "brute").collect()}


def test_independent_runs_go_side_by_side_and_keep_their_order(spark):
    import threading

    from inverse_engine.plans.store import together

    both = threading.Barrier(2, timeout=60)  # breaks unless two runs are at work at once

    def run(i):
        both.wait()
        return spark.range(i, i + 1)

    assert [df.first()[0] for df in together(spark, [lambda i=i: run(i) for i in range(4)], "test-runs")] == [0, 1, 2, 3]
    with pytest.raises(ValueError):
        together(spark, [lambda: spark.range(1), lambda: (_ for _ in ()).throw(ValueError("no"))], "test-runs")


def test_skyline_candidates_go_by_some_points_before_blocks_are_read(spark, monkeypatch):
    from inverse_engine.operators import skyline
    from inverse_engine.sources.query_sets import neighbour_query_sets

    monkeypatch.setattr(skyline, "FIRST_POINTS", 200)
    points = stored(synthetic(spark, 900, 6, seed=3), "test-points")
    index, sets = build_index(points, 32), neighbour_query_sets(points, 2, 2)
    for include in (False, True):
        rows = gathered(points, sets)
        reached = stored(skyline._candidates(index, rows, None, include), "test-candidates")
        left = skyline._not_ruled_out(reached, index, True)
        assert 0 < left.count() < reached.count() and left.columns == reached.columns
        got = {tuple(r) for r in skyline.inverse_dynamic_skyline(points, sets, index=index, include_query_objects=include).collect()}
        assert got == {tuple(r) for r in skyline.inverse_dynamic_skyline(points, sets, "brute", include_query_objects=include).collect()} and got


def test_averages_look_members_up_once(spark, monkeypatch):
    from inverse_engine.operators import common
    from inverse_engine.plans import accesses

    calls, look_up = [], common.attach_coordinates
    monkeypatch.setattr(common, "attach_coordinates", lambda *a: calls.append(1) or look_up(*a))
    points = stored(synthetic(spark, 600, 2, seed=4), "test-points")
    index, sets = build_index(points, 32), sample_query_sets(points, 2, 2, 0.05)
    got = {r["method"]: r for r in accesses.averages(index, sets, EpsRange(0.1), 1000).collect()}
    assert len(calls) == 1 and set(got) == set(accesses.METHODS)
    for method, r in got.items():
        alone = accesses.blocks_read(index, sets, EpsRange(0.1), method).agg({"requested": "sum", "read": "sum", "pages": "sum"}).first()
        assert r["n_sets"] == 2 and [r["requested"], r["read"], r["pages"]] == [alone[f"sum({c})"] / 2 for c in ("requested", "read", "pages")]
    found = accesses.inverse(points, sets, EpsRange(0.1), "brute").count()
    assert {r["results"] for r in got.values()} == {found / 2}
