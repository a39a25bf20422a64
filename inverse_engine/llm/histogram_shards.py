"""Sharding by histogram sort.

Rows are ordered by (hash of the text, doc_id). Each round counts the exact bytes and rows of radix probes inside the
intervals that still hold a wanted boundary; boundaries move until they are within the tolerance, and rows then cross one
exchange. Equal texts are neighbours in that order: a group is cut only where no boundary outside it meets the tolerance.

Edge cases: a null text has no bytes and the checksum 0, as an empty one; a null id sorts first; rows that agree in both id and
text are told apart by a number that each row gets when the keys are written; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from inverse_engine.llm.common import materialise

#: Bits that one round of probes resolves.
RADIX = 12
#: Pieces between splitters at most; the splitter table is this long and lives in the plan as a literal. A piece with more rows than
#: asked for is sorted in several tasks, by equal parts of its range of keys.
MOST_PIECES = 512
#: The order of rows: a hash of the text, the id, and the row's number.
ORDER = ("sort_key", "tie_key", "row_key")
LOWEST, HIGHEST = -(1 << 63), (1 << 63) - 1


@dataclass
class Splitter:
    """First key of a piece (one number for each column of ORDER), with the exact bytes and rows below it."""

    key: tuple[int, int, int]
    bytes_below: int
    rows_below: int


def keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        "doc_id",
        (F.octet_length(text) + F.lit(8)).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.shiftrightunsigned(F.xxhash64(text), 1).alias("sort_key"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST)).alias("tie_key"),
        F.monotonically_increasing_id().alias("row_key"),  # fixed from here on, as the keys are written
    )


#: An open interval: the keys that all its rows share, its lowest key in the next column of ORDER (None: not yet known), its bits.
Span = tuple[tuple[int, ...], int | None, int]


def _longs(values: list[int]) -> Column:
    """A literal array; as one string, which is folded once, and not a call for each number."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>")


def _passed(df: DataFrame, name: str, keys: list[tuple[int, ...]]) -> DataFrame:
    """Column `name`: how many of the ascending keys (in the first columns of ORDER) a row is at or above, by binary search in literal
    arrays, as one expression whose size does not grow with the keys."""
    columns = ORDER[: len(keys[0])] if keys else ()
    arrays = [_longs([k[i] for k in keys]) for i in range(len(columns))]

    def step(found: Column, width: Column) -> Column:
        at = found + width - 1
        passed = F.lit(True)
        for column, array in zip(reversed(columns), reversed(arrays), strict=True):
            passed = (F.col(column) > F.get(array, at)) | ((F.col(column) == F.get(array, at)) & passed)
        return F.when((at < len(keys)) & passed, found + width).otherwise(found)

    widths = F.array(*[F.lit(1 << s) for s in reversed(range(len(keys).bit_length()))])
    return df.withColumn(name, F.aggregate(widths, F.lit(0), step) if keys else F.lit(0))


def _probe(rows: DataFrame, spans: list[Span], shift: int) -> list[list[tuple[int, int, int]]]:
    """Bytes and rows by sub-interval of 2**shift keys, for each of some intervals of one depth and one number of bits, in order."""
    depth, bits = len(spans[0][0]), spans[0][2]
    column = F.col(ORDER[depth])
    found = _passed(rows, "part", [(*fixed, lowest) for fixed, lowest, _ in spans]).where("part > 0")
    same = F.lit(True)
    for i in range(depth):
        same = same & (F.col(ORDER[i]) == F.get(_longs([s[0][i] for s in spans]), F.col("part") - 1))
    low = F.get(_longs([s[1] for s in spans]), F.col("part") - 1)
    high = F.get(_longs([min(HIGHEST, s[1] + (1 << bits) - 1) for s in spans]), F.col("part") - 1)
    cell = F.shiftrightunsigned(F.when(same & (column <= high), column - low), shift)
    out: list[list[tuple[int, int, int]]] = [[] for _ in spans]
    for r in found.groupBy("part", cell.alias("cell")).agg(F.sum("size").alias("b"), F.count("*").alias("n")).where(F.col("cell").isNotNull()).collect():
        out[r["part"] - 1].append((r["cell"], r["b"], r["n"]))
    return [sorted(v) for v in out]


def _ranges(rows: DataFrame, todo: dict[Span, tuple[int, int, list[int]]], targets: list[int]) -> None:
    """Give intervals that were just opened inside one key the range that their rows fill, below and from zero on apart, as a
    difference of keys may pass 63 bits."""
    for depth in sorted({len(k[0]) for k in todo if k[1] is None}):
        fresh = [k for k in todo if k[1] is None and len(k[0]) == depth]
        column, keys = F.col(ORDER[depth]), F.struct(*[F.col(c) for c in ORDER[:depth]])
        wanted = keys.isin([F.struct(*[F.lit(x).cast("long").alias(c) for c, x in zip(ORDER, k[0], strict=False)]) for k in fresh])
        below = column < 0
        ends = rows.where(wanted).groupBy(*ORDER[:depth], below.alias("below")).agg(F.min(column).alias("lo"), F.max(column).alias("hi"), F.sum("size").alias("b"), F.count("*").alias("n")).collect()  # two rows at most for each
        for k in fresh:
            b0, n0, inside = todo.pop(k)
            for r in sorted((r for r in ends if tuple(r[c] for c in ORDER[:depth]) == k[0]), key=lambda r: not r["below"]):
                mine = [w for w in inside if targets[w] < b0 + r["b"]]
                if r["hi"] >= 0 or len(mine) == len(inside):
                    mine = inside
                if mine:
                    todo[(k[0], r["lo"], max(1, (r["hi"] - r["lo"]).bit_length()))] = (b0, n0, mine)
                inside = [w for w in inside if w not in set(mine)]
                b0, n0 = b0 + r["b"], n0 + r["n"]


def splitters(rows: DataFrame, targets: list[int], slack: list[int], total_bits: int = 63) -> list[Splitter]:
    """One splitter for each wanted number of bytes below it. At most RADIX-bit histograms of open intervals reach the driver."""
    done: dict[int, Splitter] = {}
    #: Open intervals -> (bytes below, rows below, indices of the targets inside).
    todo: dict[Span, tuple[int, int, list[int]]] = {((), 0, total_bits): (0, 0, list(range(len(targets))))}
    while todo:
        _ranges(rows, todo, targets)
        for depth, bits in sorted({(len(k[0]), k[2]) for k in todo}):
            spans = sorted(k for k in todo if len(k[0]) == depth and k[2] == bits and k[1] is not None)
            shift = max(0, bits - RADIX)
            counts = _probe(rows, spans, shift)
            for i, span in enumerate(spans):
                fixed, lowest, _ = span
                b0, n0, wanted = todo.pop(span)
                edges = [(lowest, b0, n0)]
                for cell, b, n in counts[i]:
                    edges[-1] = (lowest + (cell << shift), edges[-1][1], edges[-1][2])  # an edge moves up to the next row's cell
                    edges.append((lowest + ((cell + 1) << shift), edges[-1][1] + b, edges[-1][2] + n))
                at = 0
                for w in wanted:
                    while at + 2 < len(edges) and edges[at + 1][1] <= targets[w]:
                        at += 1
                    best = min(edges[at : at + 2], key=lambda e: abs(e[1] - targets[w]))
                    lone = at + 1 < len(edges) and edges[at + 1][2] - edges[at][2] <= 1
                    if abs(best[1] - targets[w]) <= slack[w] or lone or len(edges) < 2 or (shift == 0 and depth + 1 == len(ORDER)):
                        done[w] = Splitter((*fixed, min(best[0], HIGHEST), *[LOWEST] * (len(ORDER) - depth - 1)), best[1], best[2])
                    elif shift == 0:
                        # The copies of one key hold more than the tolerance: the boundary goes on among them, in the next column.
                        todo.setdefault(((*fixed, edges[at][0]), None, 64), (edges[at][1], edges[at][2], []))[2].append(w)
                    else:
                        todo.setdefault((fixed, edges[at][0], shift), (edges[at][1], edges[at][2], []))[2].append(w)
    return [done[i] for i in range(len(targets))]


def _sorted_in(parted: DataFrame, cuts: list[Splitter], parts: int) -> DataFrame:
    """Column `sub`: which of `parts` equal ranges of its piece's keys a row is in. In order of the rows: in a piece inside one text,
    the ranges are of ids."""
    if parts == 1:
        return parted.withColumn("sub", F.lit(0))
    ends = [(0, LOWEST, LOWEST), *[c.key for c in cuts], (HIGHEST, HIGHEST, HIGHEST)]
    low, high = ([_longs([e[i] for e in side]) for i in (0, 1)] for side in (ends[:-1], ends[1:]))
    share = lambda c, i: (F.col(c).cast("double") - F.get(low[i], F.col("piece")).cast("double")) / F.greatest(F.lit(1.0), F.get(high[i], F.col("piece")).cast("double") - F.get(low[i], F.col("piece")).cast("double"))
    one_text = F.get(low[0], F.col("piece")) == F.get(high[0], F.col("piece"))
    at = F.floor(F.when(one_text, share("tie_key", 1)).otherwise(share("sort_key", 0)) * parts)
    return parted.withColumn("sub", F.least(F.greatest(at, F.lit(0)), F.lit(parts - 1)).cast("int"))


def histogram_shards(docs: DataFrame, shards: int = 24, tolerance: float = 0.01, piece_rows: int = 20_000) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard): contiguous key ranges of near equal bytes.

    `tolerance`: how far a boundary may lie from its place, as a share of a shard's bytes (a single row may force more)."""
    rows = materialise(keyed(docs), "shard-keys")
    whole = rows.agg(F.sum("size").alias("b"), F.count("*").alias("n")).first()
    total, n = whole["b"] or 0, whole["n"]
    per = max(1, min(MOST_PIECES // shards, max(min(8, n // (shards * 100)), -(-n // (shards * piece_rows)))))
    pieces = shards * per
    targets = [total * i // pieces for i in range(1, pieces)]
    ideal = total / shards
    slack = [int(ideal * tolerance) if i % per == 0 else int(ideal / per / 4) for i in range(1, pieces)]
    cuts = splitters(rows, targets, slack) if n else []
    # A loose inner cut may have passed a shard's boundary: keep the order.
    for i in reversed(range(len(cuts) - 1)):
        if cuts[i].key > cuts[i + 1].key:
            cuts[i] = cuts[i + 1]
    below = [0, *[c.rows_below for c in cuts]]
    first = [below[i - i % per] for i in range(len(below))]
    base = _longs([a - b for a, b in zip(below, first, strict=True)])
    most = max(b - a for a, b in zip(below, [*below[1:], n], strict=True)) if n else 0
    parts = max(1, -(-most // piece_rows))
    placed = _sorted_in(_passed(rows, "piece", [c.key for c in cuts]), cuts, parts)
    before = F.lit(0)
    if parts > 1:
        # Rows of a piece's earlier ranges: a table of one row for each task, joined on the window's own keys.
        ranges = placed.groupBy("piece", "sub").agg(F.count("*").alias("rows"))
        ranges = ranges.select("piece", "sub", (F.sum("rows").over(Window.partitionBy("piece").orderBy("sub")) - F.col("rows")).alias("before"))
        placed, before = placed.join(ranges, ["piece", "sub"]), F.col("before")
    place = F.row_number().over(Window.partitionBy("piece", "sub").orderBy(*ORDER))
    return placed.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        F.floor(F.col("piece") / F.lit(per)).cast("int").alias("shard"),
        (F.get(base, F.col("piece")) + before + place - 1).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
