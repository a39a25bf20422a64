"""How many sets, blocks and objects each filter leaves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.operators import eps_range, knn, skyline
from inverse_engine.operators.common import gathered
from inverse_engine.operators.framework import EpsRange, Nearest, inverse
from inverse_engine.plans.blocks import build_index
from inverse_engine.plans.store import stored


def explain_filters(points: DataFrame, sets: DataFrame, predicate, rows_per_block: int = 256) -> DataFrame:
    """(step, stage, n): sets asked, sets that validation leaves, (set, block) pairs left, candidates, results."""
    index = build_index(points, rows_per_block)
    d = index.d
    rows = gathered(points, sets)
    stages: list[tuple[str, DataFrame]] = [("sets", rows)]
    if isinstance(predicate, EpsRange):
        live = eps_range.eps_validate(rows.withColumn("eps", F.lit(float(predicate.eps))), d, predicate.closed).where("alive")
        hit = eps_range.eps_blocks(index.blocks, eps_range.eps_window(live, d), d)
        stages += [("live sets", live), ("blocks", hit), ("blocks accepted unread", hit.where("inner")), ("candidates", index.points.join(hit.select("set_id", "cell"), "cell"))]
    elif isinstance(predicate, Nearest):
        live = knn.knn_validate(rows.withColumn("k", F.lit(int(predicate.k)))).where("alive")
        alive, left = knn.alive_blocks(index, live, hull=True)
        alive = stored(alive, "report-blocks")
        stages += [("live sets", left), ("blocks", alive), ("points of blocks", index.points.join(alive.select("set_id", "cell"), "cell")), ("candidates", knn._candidates(index, live, None, True, False))]
        if d <= 3:
            stages.append(("hull members", knn.hull_members(points, live, d)))
    else:
        live = skyline.sky_validate(rows, d).where("alive").drop("alive")
        stages += [("live sets", live), ("not pruned by pairs", skyline.sky_query_prune(points, live, d)), ("candidates", skyline._candidates(index, live, None, False))]
    stages.append(("results", inverse(points, sets, predicate, index=index)))
    out = None
    for step, (stage, frame) in enumerate(stages):
        one = frame.agg(F.count("*").alias("n")).select(F.lit(step).alias("step"), F.lit(stage).alias("stage"), "n")
        out = one if out is None else out.unionByName(one)
    return out
