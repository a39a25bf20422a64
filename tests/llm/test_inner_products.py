"""Exact top-k against all products."""

import collections
import math
import random

import pytest

from inverse_engine.llm import inner_products


def brute(rows, every, k):
    whole = []
    for i, v in rows:
        if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v):
            whole.append((i, [math.floor(1024 * x) for x in v]))
    out = collections.Counter()
    for n, (q, v) in enumerate(whole):
        if q % every == 0:
            scores = sorted((-sum(a * b for a, b in zip(v, w)), i) for j, (i, w) in enumerate(whole) if j != n)[:k]
            out.update((q, r, i, -s) for r, (s, i) in enumerate(scores, 1))
    return out


@pytest.mark.parametrize("block, queries, bands, classes", [(4096, 1024, 1024, 256), (40, 1024, 1024, 256), (20, 4, 5, 3), (10, 3, 1, 1)])
def test_top_products(spark, block, queries, bands, classes, monkeypatch):
    for name, value in (("BLOCK", block), ("QUERIES", queries), ("BANDS", bands), ("CLASSES", classes)):
        monkeypatch.setattr(inner_products, name, value)
    rng = random.Random(block)
    rows = [(i, [rng.gauss(0, 1) * rng.choice([0.1, 1, 3]) for _ in range(9)]) for i in range(300)]
    rows += [(300 + i, rows[i][1]) for i in range(20)] + [(400, None), (401, [math.nan] * 9), (402, [None] * 9), (403, [math.inf] * 9), (None, [1.0] * 9), (404, [0.0] * 9), (420, [0.0] * 9)]
    rows += [(40, rows[11][1]), (40, rows[40][1]), (41, rows[12][1])]  # ids that repeat, with another and the same vector
    df = spark.createDataFrame([(i, v, "x", 7) for i, v in rows], "vec_id long, embedding array<double>, score string, row long")
    got = collections.Counter(tuple(r) for r in inner_products.top_inner_products(df, "vec_id", "embedding", 20, 7).collect())
    assert got == brute(rows, 20, 7)
    assert inner_products.top_inner_products(df.limit(0), "vec_id", "embedding", 20, 7).count() == 0


def test_unlike_lengths(spark, monkeypatch):
    """Most blocks are too short for any query."""
    for name, value in (("BLOCK", 50), ("QUERIES", 5)):
        monkeypatch.setattr(inner_products, name, value)
    rng = random.Random(1)
    rows = [(i, [abs(rng.gauss(0, 1)) * (30 if i < 100 else 0.01) for _ in range(6)]) for i in range(1000)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = collections.Counter(tuple(r) for r in inner_products.top_inner_products(frame, "vec_id", "embedding", 20, 5).collect())
    assert got == brute(rows, 20, 5)
    plan = inner_products.top_inner_products(frame, "vec_id", "embedding", 20, 5)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan
