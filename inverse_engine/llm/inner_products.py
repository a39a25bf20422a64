"""Exact top-k inner products: norm-sorted candidates, partial sums in a rotated basis, Cauchy-Schwarz bounds on the rest.

Vectors are whole numbers, so scores are exact. The singular vectors of the candidates (from one d x d sum over all of them)
give a basis whose first coordinates carry most of an inner product; what the others can add is at most the product of the two
residual lengths. Candidates go into bands by descending length, and each band into blocks. The first block gives each query a
first k-th score, and so the least length that a candidate of use to it has; queries go into lots by that length. Only blocks and
lots whose lengths can reach each other meet. A task has one block and one lot, walks the candidates from the longest in small
steps, stops when length times length cannot reach the k-th score, and finishes only the sums whose bound can.

Edge cases: vectors that are null or hold a null or non-finite component take no part, nor do rows without an id; shorter vectors
count as padded with zeros; rows that repeat an id are candidates and queries of their own, each without itself; ties go to the
smaller id; an empty table gives an empty result. Products that could pass 2**53 are summed in whole numbers of any length; a
score beyond a long is given, and ranked, as the nearest long.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine.llm.common import materialise, one_thread, ship

#: Candidates in a block, queries in a block, candidates in a step, rotated coordinates of the partial sum.
BLOCK, QUERIES, STEP, LEADING = 4096, 1024, 512, 16
#: Bands of candidates by length, and classes of queries by the length that they need, at most: what the driver holds and the plan
#: names. Beyond it, bands and classes hold more blocks and lots.
BANDS, CLASSES = 1024, 256


def whole_vectors(frame: DataFrame, id_column: str, vector_column: str, scale: int) -> DataFrame:
    """(vec_id, v: floor(scale * x) as doubles, len2): usable vectors only."""
    v = F.transform(F.col(vector_column), lambda x: F.floor(x.cast("double") * scale).cast("double"))
    fine = F.col(vector_column).isNotNull() & ~F.exists(F.col(vector_column), lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    rows = frame.where(fine).select(F.col(id_column).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull())
    return rows.withColumn("len2", F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))


def gram(rows: DataFrame, d: int) -> np.ndarray:
    """Sum of the outer products: one d x d matrix for each partition, added up in the cluster."""

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d, d))
        for batch in batches:
            x = _matrix(batch.column(0).to_pylist(), d)
            x = x / np.maximum(1.0, np.abs(x).max(axis=1, keepdims=True)) if len(x) else x
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d)), pa.array(list(total), pa.list_(pa.float64()))], ["row", "sums"])

    sums = rows.select("v").mapInArrow(part, "row long, sums array<double>").groupBy("row").agg(*[F.sum(F.get("sums", F.lit(i))).alias(f"s{i}") for i in range(d)])
    out = np.zeros((d, d))
    for r in sums.collect():  # d rows
        out[r["row"]] = r[1:]
    return out


def _matrix(vectors: list, d: int) -> np.ndarray:
    out = np.zeros((len(vectors), d))
    for row, v in zip(out, vectors, strict=True):
        row[: len(v)] = v
    return out


def _products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact inner products of rows of whole numbers (all pairs), as numbers that fit a long."""
    if len(a) == 0 or len(b) == 0 or np.abs(a).max(initial=0) * np.abs(b).max(initial=0) * a.shape[1] < 2**53:
        return (a @ b.T).astype(np.int64)
    exact = np.array([[int(x) for x in row] for row in a], dtype=object) @ np.array([[int(x) for x in row] for row in b], dtype=object).T
    return np.clip(exact, -(2**63), 2**63 - 1).astype(np.int64)


def search(query_rows: np.ndarray, q: np.ndarray, floor: np.ndarray, rows_: np.ndarray, ids: np.ndarray, c: np.ndarray, basis: np.ndarray, k: int) -> list[tuple[int, int, int]]:
    """(query's row, vec_id, score) of each query's k best in this block that reach `floor`; candidates come by descending length."""
    lead = min(LEADING, basis.shape[1])
    qr, cr = q @ basis, c @ basis
    q_length, c_length = np.linalg.norm(q, axis=1), np.linalg.norm(c, axis=1)
    q_rest, c_rest = np.linalg.norm(qr[:, lead:], axis=1), np.linalg.norm(cr[:, lead:], axis=1)
    kth = floor.astype(np.float64)
    best: list[list[tuple[int, int]]] = [[] for _ in query_rows]
    slack = 1e-9 * (q_length * c_length.max(initial=0)) + 1e-6
    for start in range(0, len(ids), STEP):
        own = slice(start, start + STEP)
        live = np.flatnonzero(q_length * c_length[start] + slack >= kth)
        if not live.size:
            break
        bound = qr[live, :lead] @ cr[own, :lead].T + q_rest[live, None] * c_rest[None, own]
        possible = (bound + slack[live, None] >= kth[live, None]) & (query_rows[live, None] != rows_[None, own])
        rows = np.flatnonzero(possible.any(axis=1))
        if not rows.size:
            continue
        columns = np.flatnonzero(possible[rows].any(axis=0))
        scores = _products(q[live[rows]], c[own][columns])
        own_ids = ids[own][columns]
        for r, i in enumerate(live[rows].tolist()):
            mask = possible[rows[r], columns] & (scores[r] >= kth[i])
            if not mask.any():
                continue
            merged = best[i] + list(zip((-scores[r][mask]).tolist(), own_ids[mask].tolist(), strict=True))
            merged.sort()
            best[i] = merged[:k]
            if len(best[i]) == k:
                kth[i] = max(kth[i], -best[i][-1][0])
    return [(int(query_rows[i]), v, -s) for i, found in enumerate(best) for s, v in found]


def _quantiles(rows: DataFrame, column: str, parts: int) -> list[float]:
    """Ascending cuts of a column into about equal parts, from a sketch."""
    if parts < 2:
        return []
    found = rows.agg(F.percentile_approx(column, [i / parts for i in range(1, parts)], 10_000).alias("p")).first()["p"]
    return sorted({float(x) for x in found or []})


def _at_or_above(column: Column, cuts: list[float]) -> Column:
    """How many of the ascending cuts the column is at or above: binary search in one literal array."""
    if not cuts:
        return F.lit(0)
    array = F.lit(cuts)
    widths = F.array(*[F.lit(1 << s) for s in reversed(range(len(cuts).bit_length()))])
    return F.aggregate(widths, F.lit(0), lambda at, w: F.when((at + w <= len(cuts)) & (column >= F.get(array, at + w - 1)), at + w).otherwise(at))


def _dealt(counted: list, name: str, most: int) -> dict[int, dict]:
    """For each band or class, in order: its figures, the number of its first part, and how many parts of at most about `most` rows it has."""
    out, at = {}, 0
    for r in sorted(counted, key=lambda r: r[name]):
        out[r[name]] = r.asDict() | {"first": at, "parts": -(-r["n"] // most)}
        at += out[r[name]]["parts"]
    return out


def _of(column: str, values: dict[int, int]) -> Column:
    return F.get(F.lit([values.get(i, 0) for i in range(max(values, default=0) + 1)]), F.col(column))


def _part_of(column: str, dealt: dict[int, dict], seed: int) -> Column:
    first, parts = (_of(column, {i: x[key] for i, x in dealt.items()}) for key in ("first", "parts"))
    return (first + F.pmod(F.xxhash64("row", F.lit(seed)), F.greatest(parts, F.lit(1)))).cast("int")


def top_inner_products(vectors: DataFrame, id_column: str, vector_column: str, every: int, k: int, scale: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score) for all rows whose id is divisible by `every`, against all other rows."""
    ship(vectors.sparkSession)
    # Rows get a number, fixed as they are written: ids may repeat.
    rows = materialise(whole_vectors(vectors, id_column, vector_column, scale).withColumn("row", F.monotonically_increasing_id()), "inner-vectors")
    facts = rows.agg(F.max(F.size("v")).alias("d"), F.count("*").alias("n"), F.count_if(F.col("vec_id") % every == 0).alias("m")).first()
    d, n, m = max(1, facts["d"] or 1), facts["n"], facts["m"]
    basis = np.linalg.eigh(gram(rows, d))[1][:, ::-1].copy()

    # Bands by descending length, from a quantile sketch; a hash of the row's number deals a band into blocks.
    cuts = _quantiles(rows, "len2", min(BANDS, -(-n // BLOCK)))
    banded = rows.withColumn("band", F.lit(len(cuts)) - _at_or_above(F.col("len2"), cuts))
    bands = _dealt(banded.groupBy("band").agg(F.count("*").alias("n"), F.max("len2").alias("most")).collect(), "band", BLOCK)  # BANDS rows at most
    blocks = sum(b["parts"] for b in bands.values())
    dealt = materialise(banded.select("row", "vec_id", "v", "len2", "band", _part_of("band", bands, 7).alias("block")), "inner-blocks")
    queries = dealt.where(F.col("vec_id") % every == 0).select("row", "vec_id", "v", "len2")
    lots = max(1, -(-m // QUERIES))

    def task(frame: pd.DataFrame) -> pd.DataFrame:
        one_thread()
        asked, given = frame[frame["asked"]], frame[~frame["asked"]].sort_values(["len2", "vec_id"], ascending=[False, True], kind="stable")
        found = search(asked["row"].to_numpy(), _matrix(asked["v"].tolist(), d), asked["floor"].to_numpy(), given["row"].to_numpy(), given["vec_id"].to_numpy(), _matrix(given["v"].tolist(), d), basis, k)
        of = dict(zip(asked["row"].tolist(), asked["vec_id"].tolist(), strict=True))
        return pd.DataFrame([(q, of[q], v, s) for q, v, s in found], columns=["row", "query_id", "vec_id", "score"]).astype("int64")

    lowest = -(1 << 63)

    def run(asked: DataFrame, given: DataFrame) -> DataFrame:
        """asked has `lot` and an array `blocks`, given has `block` and an array `lots`; each pair that both name is one task."""
        q = asked.withColumn("block", F.explode("blocks")).select("lot", "block", "row", "vec_id", "v", F.lit(0.0).alias("len2"), "floor", F.lit(True).alias("asked"))
        c = given.withColumn("lot", F.explode("lots")).select("lot", "block", "row", "vec_id", "v", "len2", F.lit(lowest).alias("floor"), F.lit(False).alias("asked"))
        return q.unionByName(c).groupBy("lot", "block").applyInPandas(task, "row long, query_id long, vec_id long, score long")

    # The first block: no k-th scores are known.
    first = queries.select("*", F.pmod(F.xxhash64("row", F.lit(3)), F.lit(lots)).cast("int").alias("lot"), F.lit(lowest).alias("floor"), F.array(F.lit(0)).alias("blocks"))
    start = materialise(run(first, dealt.where("block = 0").withColumn("lots", F.sequence(F.lit(0), F.lit(lots - 1)))), "inner-seeds")
    found = start
    if blocks > 1:
        enough = start.groupBy("row").agg(F.count("*").alias("found"), F.min("score").alias("least")).where(F.col("found") >= k).select("row", "least")
        asked = queries.join(enough, "row", "left").withColumn("floor", F.coalesce("least", F.lit(lowest)))
        length, longest = F.sqrt("len2"), max(b["most"] for b in bands.values()) ** 0.5
        spare = (F.col("floor") - 1e-6) / length - 1e-9 * longest
        asked = asked.withColumn("need", F.when(F.col("least").isNull() | ((length == 0) & (F.col("floor") <= 0)), 0.0).when(length == 0, F.lit(float("inf"))).otherwise(F.greatest(spare, F.lit(0.0)) * (1 - 1e-12)))
        asked = materialise(asked.select("row", "vec_id", "v", "floor", "need"), "inner-asked")
        needs = _quantiles(asked, "need", min(CLASSES, lots))
        classed = asked.withColumn("class", _at_or_above(F.col("need"), needs))
        classes = _dealt(classed.groupBy("class").agg(F.count("*").alias("n"), F.min("need").alias("least")).collect(), "class", QUERIES)  # CLASSES rows at most
        # Lengths fall with bands and needs rise with classes: each class meets the first bands, each band the first classes.
        met = {c: sum(b["parts"] for b in bands.values() if b["most"] ** 0.5 >= x["least"]) for c, x in classes.items()}
        asks = {b: sum(c["parts"] for c in classes.values() if x["most"] ** 0.5 >= c["least"]) for b, x in bands.items()}
        q = classed.withColumn("upto", _of("class", met)).where("upto > 1").select("row", "vec_id", "v", "floor", _part_of("class", classes, 3).alias("lot"), F.sequence(F.lit(1), F.col("upto") - 1).alias("blocks"))
        c = dealt.where("block > 0").withColumn("upto", _of("band", asks)).where("upto > 0").withColumn("lots", F.sequence(F.lit(0), F.col("upto") - 1))
        found = start.unionByName(run(q, c))
    rank = F.row_number().over(Window.partitionBy("row").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
