"""The block index: points clustered by equi-depth cells, and a small table of each block's box and count.

Cells are numbered in Morton order, so a prefix of a cell's number is a larger cell. Points are written sorted by cell, in
folders by such a prefix (`zone`), so that a query reads the folders that its blocks are in."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property
from math import log2

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from inverse_engine.functions.geometry import at, columns, coordinates
from inverse_engine.plans.store import PLAIN, new_path, stored
from inverse_engine.sources.points import dimension

#: Entries of the level that is broadcast: block tables of more rows are reached through one of at most so many prefixes.
TOP_BITS = 12
#: Folders of points, at most, as bits; points that a folder holds, at least, about (opening a file takes longer than writing some
#: thousand points to it); bits of a dimension's cuts, at most; points that a task writes, about.
ZONE_BITS, ZONE_POINTS, MOST_BITS, FILE_POINTS = 8, 50_000, 12, 250_000
#: Rows that a task sorts at once for the cuts; values that stand for them, at least, in each dimension, and times the cuts.
CHUNK, CHUNK_VALUES, VALUES_A_CUT = 1_000_000, 4_096, 16


@dataclass
class Index:
    """points has columns `cell` and `zone`; blocks has (cell, lo, hi, cnt); cells have `width` bits, of which zones are the first."""

    points: DataFrame
    blocks: DataFrame
    d: int
    width: int
    zone_bits: int = ZONE_BITS

    @cached_property
    def n_blocks(self) -> int:
        return self.blocks.count()

    @property
    def zone_shift(self) -> int:
        return max(0, self.width - self.zone_bits)

    def read(self, hit: DataFrame) -> DataFrame:
        """The points of the zones that hold the blocks of `hit`, which has `cell`: 2**ZONE_BITS numbers reach the driver."""
        zones = [r[0] for r in hit.select(F.shiftright("cell", self.zone_shift)).distinct().collect()]
        return self.points.where(F.col("zone").isin(zones))


def placer(cuts: list[list[float]], bits: int) -> Callable[[list[np.ndarray]], np.ndarray]:
    """The Morton numbers of how many of the ascending cuts of each dimension places are at or above."""
    d = len(cuts)
    ascending = [np.array(c, dtype=np.float64) for c in cuts]
    spread = [np.array([sum((n >> b & 1) << (b * d + i) for b in range(bits)) for n in range(1 << bits)], dtype=np.int64) for i in range(d)]

    def cells(x: list[np.ndarray]) -> np.ndarray:
        cell = np.zeros(len(x[0]), dtype=np.int64)
        for c, to, own in zip(ascending, spread, x, strict=True):
            cell += to[np.searchsorted(c, own, side="right")]
        return cell

    return cells


def placed_in_cells(points: DataFrame, cuts: list[list[float]], bits: int, ends: np.ndarray | None = None) -> DataFrame:
    """points with `cell`, by the cuts of the first dimensions, and, if `ends` are given, `file`: how many of these ascending cells a cell is above."""
    cells = placer(cuts, bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cell = cells([batch.column(f"x{i}").to_numpy(zero_copy_only=False) for i in range(len(cuts))])
            batch = batch.append_column("cell", pa.array(cell))
            yield batch if ends is None else batch.append_column("file", pa.array(np.searchsorted(ends, cell).astype(np.int32)))

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema]
    return points.mapInArrow(run, ", ".join([*fields, "cell bigint"] + ["file int"] * (ends is not None)))


def summary(points: DataFrame, used: int, values: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], list[np.ndarray]]:
    """Of all rows: for each of the first dimensions ascending values and how many rows each stands for, at most about one part in
    `values` of them; and the places of at most as many rows of each CHUNK, evenly spaced. `values` numbers of a chunk reach the driver."""

    def shortened(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        # The middle row of each of equal shares of the ordered rows stands for the share.
        share = np.linspace(0, len(x), min(values, len(x)) + 1)
        return np.sort(x)[((share[1:] + share[:-1]) / 2).astype(np.int64)], np.diff(share)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []

        def sent() -> Iterator[pa.RecordBatch]:
            x = [np.concatenate(c) for c in zip(*held, strict=True)]
            step = max(1, -(-len(x[0]) // values))
            for i, c in enumerate(x):
                v, w = shortened(c)
                yield pa.RecordBatch.from_pydict({"i": pa.array([i], pa.int32()), "v": [v], "w": [w], "rows": [c[::step]]})

        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(f"x{i}").to_numpy(zero_copy_only=False) for i in range(used)])
            if sum(len(h[0]) for h in held) >= CHUNK:
                yield from sent()
                held.clear()
        if held:
            yield from sent()

    got = points.select(*coordinates(used)).mapInArrow(run, "i int, v array<double>, w array<double>, rows array<double>").toArrow()
    own = [got.filter(pyarrow.compute.equal(got["i"], i)) for i in range(used)]
    flat = lambda t, c: pyarrow.compute.list_flatten(t[c]).to_numpy()
    merged = []
    for t in own:
        v, w = flat(t, "v"), flat(t, "w")
        order = np.argsort(v, kind="stable")
        merged.append((v[order], w[order]))
    return merged, [flat(t, "rows") for t in own]


def build_index(points: DataFrame, rows_per_block: int = 1024, most_dimensions: int = 6, kept: bool = True) -> Index:
    """Cuts at approximate quantiles, over all rows, of each of the first dimensions, Morton order of the cells. kept: points and blocks
    are written once, and read by every use of the index."""
    d = dimension(points)
    used = min(d, most_dimensions)
    if kept:
        points = stored(points, "index-points", plain=True)  # read for the count, the cuts, the ranges of cells and the writing
    n = points.count()
    bits = max(1, min(MOST_BITS, round(log2(max(1.0, n / rows_per_block)) / used)))
    merged, some = summary(points, used, max(CHUNK_VALUES, VALUES_A_CUT << bits))
    cuts = []
    for v, w in merged:
        upto = np.cumsum(w)
        at_ = np.searchsorted(upto, np.arange(1, 1 << bits) / (1 << bits) * (upto[-1] if len(v) else 0))
        cuts.append(sorted(set(v[np.minimum(at_, len(v) - 1)].tolist())) if len(v) else [])
    files = max(1, n // FILE_POINTS, min(n // ZONE_POINTS, points.sparkSession.sparkContext.defaultParallelism))
    # Files of about equally many points, by the cells of evenly spaced rows: every row goes to the file of its own cell.
    cells = np.sort(placer(cuts, bits)(some))
    ends = np.unique(cells[np.arange(1, files) * len(cells) // files]) if len(cells) else np.zeros(0, dtype=np.int64)
    placed = placed_in_cells(points, cuts, bits, ends if kept else None)
    zone_bits = max(0, min(ZONE_BITS, round(log2(max(1.0, n / ZONE_POINTS)))))
    placed = placed.withColumn("zone", F.shiftright("cell", max(0, used * bits - zone_bits)))
    index = Index(placed, summarise(placed, d), d, used * bits, zone_bits)
    if not kept:
        return index
    path = new_path(points.sparkSession, "index")
    write_index(index, path, len(ends) + 1)
    return read_index(points.sparkSession, path)


def summarise(placed: DataFrame, d: int) -> DataFrame:
    names = coordinates(d)
    return placed.groupBy("cell").agg(F.array(*[F.min(n) for n in names]).alias("lo"), F.array(*[F.max(n) for n in names]).alias("hi"), F.count("*").alias("cnt"))


def top_level(index: Index, alias: str = "up") -> tuple[DataFrame, int]:
    """(up, lo, hi, cnt) of at most 2**TOP_BITS prefixes of cells, and how far a cell is shifted to its prefix."""
    shift = max(0, index.width - TOP_BITS)
    boxes = [F.array(*[f(F.get(c, F.lit(i))) for i in range(index.d)]).alias(c) for c, f in (("lo", F.min), ("hi", F.max))]
    return index.blocks.groupBy(F.shiftright("cell", shift).alias(alias)).agg(*boxes, F.sum("cnt").alias("cnt")), shift


def meeting(index: Index, asked: DataFrame, test: Callable[[list[Column], list[Column]], Column]) -> DataFrame:
    """asked with cell, lo, hi, cnt of each block whose box passes the test. A test must hold for a box if it does for a part of it.

    Only the level of at most 2**TOP_BITS entries is broadcast; blocks below it are reached by equality of their prefix."""
    lo, hi = at(F.col("lo"), index.d), at(F.col("hi"), index.d)
    if index.n_blocks <= 1 << TOP_BITS:
        return asked.join(F.broadcast(index.blocks), test(lo, hi))
    top, shift = top_level(index)
    reached = asked.join(F.broadcast(top), test(lo, hi)).select(*asked.columns, "up")
    return reached.join(index.blocks.withColumn("up", F.shiftright("cell", shift)), "up").where(test(lo, hi)).drop("up")


def rollup_blocks(blocks: DataFrame, d: int, levels: int) -> DataFrame:
    """All levels: (level, cell, parent, lo, hi, cnt); a parent is its children's Morton prefix."""
    out = level = blocks.select(F.lit(0).alias("level"), "cell", F.shiftright("cell", d).alias("parent"), "lo", "hi", "cnt")
    for k in range(1, levels + 1):
        boxes = [F.array(*[f(F.get(c, F.lit(i))) for i in range(d)]).alias(c) for c, f in (("lo", F.min), ("hi", F.max))]
        level = level.groupBy(F.col("parent").alias("up")).agg(*boxes, F.sum("cnt").alias("cnt")).select(F.lit(k).alias("level"), F.col("up").alias("cell"), F.shiftright("up", d).alias("parent"), "lo", "hi", "cnt")
        out = out.unionByName(level)
    return out


def write_index(index: Index, path: str, files: int = 64) -> None:
    """Points as Parquet by zone, near cells in one file, sorted inside it, so that row groups carry narrow ranges; the blocks beside them."""
    if "file" in index.points.columns:
        ordered = index.points.repartitionById(files, "file").drop("file").sortWithinPartitions("cell")
    else:
        ordered = index.points.repartitionByRange(files, "cell").sortWithinPartitions("cell")
    ordered.write.options(**PLAIN).partitionBy("zone").parquet(f"{path}/points")
    written = index.points.sparkSession.read.parquet(f"{path}/points")
    summarise(written, index.d).withColumn("width", F.lit(index.width)).withColumn("zone_bits", F.lit(index.zone_bits)).coalesce(max(1, files // 16)).write.parquet(f"{path}/blocks")


def read_index(spark: SparkSession, path: str) -> Index:
    points = spark.read.parquet(f"{path}/points").withColumn("zone", F.col("zone").cast("long"))
    blocks = spark.read.parquet(f"{path}/blocks")
    bits = blocks.select("width", "zone_bits").first() or (1, ZONE_BITS)
    return Index(points, blocks.drop("width", "zone_bits"), dimension(points), *bits)


def page_model(rows: DataFrame, d: int, page_bytes: int = 1024) -> DataFrame:
    """Pages that the rows of `cnt` points would fill, at 8 bytes a number."""
    return rows.withColumn("pages", F.ceil(F.col("cnt") * (8 * d + 8) / page_bytes).cast("long"))


__all__ = ["Index", "build_index", "columns", "meeting", "page_model", "read_index", "rollup_blocks", "summarise", "top_level", "write_index"]
