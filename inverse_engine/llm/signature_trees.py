"""N-gram Jaccard join by signature trees.

A document is the set of its word shingles, hashed to 64 bits. Equal sets are one node. Trees are rooted in the cluster:

* Root levels. Sizes fall into classes; a class is where a set of its sizes meets the larger sets that it may link with. Two sets
  that link differ in at most D shingles there. Shingles are dealt by hash into slices, and nodes that agree on a slice of two
  shingles or more share a cell. Small classes have D + 1 slices, so that linked sets agree on one, and a slice with less in it
  is asked for together with each slice of a second dealing. Large classes have as many slices, in as many dealings, as leave a
  pair that links a chance below MISSED to agree on none (the order of a collision of hashes). Cells that share a node share a
  branch. Each branch is one tree (a long branch: several, see below).
* Inner levels. A tree's leaves hold a few similar sets; every node holds the OR of its sets' bitmaps and their range of
  sizes. The traversal walks pairs of nodes and drops a pair whose sizes cannot meet the threshold, whose common bits
  cannot hold the overlap that it needs, or whose members are all linked already. Sets that are left are compared whole.

Only links that join two groups come out, so a group of n near copies gives n - 1 rows, not n * n. A branch beyond
BRANCH nodes is dealt into parts; each part also holds the branch's first node. If that leaves nodes apart from the first
one's group, these are joined with all parts, part by part. No link is lost on any of these ways.

Edge cases: null, empty and blank texts have the empty set and link with nothing, not even each other; texts of one or two
words are one shingle; repeated rows are one node; rows that share an id but not the text are nodes of their own; a null id links
like any other and is never a component's smallest id unless all its ids are null; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import discard, discard_since, materialise, release, ship, steps
from inverse_engine.llm.components import components

#: Ratio of the bounds of a size class; nodes of a part of a branch; sets of a leaf; children of a tree node.
CLASS_RATIO, BRANCH, LEAF, FANOUT = 1.3, 192, 6, 4
#: Up to so many differences, slices are exhaustive; the chance that a link at the very threshold shares no cell, above it.
FEW_DIFFERENCES, MISSED = 16, 1e-12
#: Words that a worker remembers; up to so many nodes are broadcast to fetch their texts, more are joined by exchange.
REMEMBERED, MOST_BROADCAST = 120_000, 200_000
#: Stands for a null id where rows are found again.
NO_ID = -(1 << 63)
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def slices(batches: Iterator[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """Smaller batches: texts and keys of so many rows are held at once."""
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > REMEMBERED:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value


def shingles(text: str | None, words: WordHashes, n: int) -> np.ndarray:
    """Sorted hashes of the set. bytes.lower() and bytes.split() know exactly A-Z and the six ASCII spaces."""
    own = (text or "").encode().lower().split()
    h = np.fromiter(map(words.__getitem__, own), dtype=np.uint64, count=len(own))
    if len(h) == 0:
        return h
    if len(h) < n:
        return mixed(np.array([xxhash.xxh3_64_intdigest(b" ".join(own), seed=len(own))], dtype=np.uint64))
    total = h[: len(h) - n + 1].copy()
    for k in range(1, n):
        total = total * _B + h[k : len(h) - n + 1 + k]
    return np.unique(mixed(total))


def identity(own: np.ndarray) -> int:
    """One number for a set."""
    parts = np.array([own.sum(), np.bitwise_xor.reduce(mixed(own ^ _B)), len(own)], dtype=np.uint64) * np.array([_A, _C, _B])
    return int(mixed(parts.sum(keepdims=True)).view(np.int64)[0])


class Classes:
    """Size classes, and how the shingles of the sets that meet in each are dealt, for a threshold of `part` in `whole`.

    Class j is where a set of low[j] to low[j + 1] - 1 shingles meets sets of its size or larger."""

    def __init__(self, part: int, whole: int):
        self.part, self.whole = part, whole
        low = [1]
        while low[-1] < 1 << 31:
            low.append(max(low[-1] + 1, int(np.ceil(low[-1] * CLASS_RATIO))))
        self.low = np.array(low)
        self.plans = [self._plan(j) for j in range(len(low) - 1)]

    def _plan(self, j: int) -> tuple[int, int, bool]:
        """Slices, dealings, and whether D + 1 slices leave nothing to chance; no slices where only equal sets link."""
        small = int(self.low[j + 1]) - 1
        # |A| + |B| - 2 |A & B| is at most (|A| + |B|) (1 - t) / (1 + t).
        most = (small + small * self.whole // self.part) * (self.whole - self.part) // (self.whole + self.part)
        if most == 0:
            return 0, 0, True
        if most < FEW_DIFFERENCES:
            return most + 1, 1, True
        m = np.unique(np.geomspace(max(4, most // 24), most + 1, 400).astype(np.int64)).astype(np.float64)
        mean = self.low[j] / m
        poor = np.exp(-mean) * (1 + mean)
        rich = np.maximum(m * (1 - poor) - 2 * np.sqrt(m * poor), 0)
        # All rich slices must hold a difference for a link to go unseen in one dealing.
        dealings = np.ceil(np.log(MISSED) / np.minimum(rich * np.log1p(-np.exp(most * np.log1p(-1 / m))), -1e-9))
        at = int(np.argmin(m * dealings))
        return int(m[at]), int(dealings[at]), False

    @staticmethod
    def _slice_keys(own: np.ndarray, m: int, j: int, turn: int) -> tuple[np.ndarray, np.ndarray]:
        dealt = own if turn == 0 else mixed(own ^ (_C * np.array([2 * turn + 1], dtype=np.uint64)))
        place = (dealt % np.uint64(m)).astype(np.int64)
        sums = np.zeros(m, dtype=np.uint64)
        np.add.at(sums, place, mixed(own ^ _A))
        return mixed(sums * _C + np.arange(m, dtype=np.uint64) * _B + np.array([16 * (j + 1) + turn], dtype=np.uint64) * _A), np.bincount(place, minlength=m)

    def keys(self, own: np.ndarray) -> np.ndarray:
        """The cells of a set, in its own class and in the classes of the smaller sets that it may link with."""
        j = int(np.searchsorted(self.low, len(own), side="right")) - 1
        out = [np.array([], dtype=np.uint64)]
        while j >= 0 and len(own) * self.part <= self.whole * (int(self.low[j + 1]) - 1):
            m, dealings, exhaustive = self.plans[j]
            for turn in range(dealings):
                keys, counts = self._slice_keys(own, m, j, turn)
                poor = counts <= 1  # unlike sets meet in slices with next to nothing in them
                out.append(keys[~poor])
                if exhaustive and poor.any():
                    again, _ = self._slice_keys(own, m, j, 1)
                    out.append(mixed(keys[poor][:, None] * _A + again[None, :] * _B).ravel())
            j -= 1
        return np.concatenate(out).view(np.int64)


class Tree:
    """Static arrays: node i of a level covers FANOUT nodes of the level below."""

    def __init__(self, sets: list[np.ndarray], width: int):
        sizes = np.array([len(s) for s in sets])
        # Near sets mostly agree in their least hashes, and so become neighbours.
        least = [np.sort(mixed(s ^ _C))[:3].tolist() for s in sets]
        self.order = sorted(range(len(sets)), key=lambda i: (least[i], sizes[i]))
        self.bits = np.zeros((len(sets), width // 64), dtype=np.uint64)
        for row, i in enumerate(self.order):
            at = (sets[i] >> np.uint64(7)) % np.uint64(width)
            np.bitwise_or.at(self.bits[row], (at >> np.uint64(6)).astype(np.int64), np.uint64(1) << (at & np.uint64(63)))
        self.sizes = sizes[self.order]
        self.excess = self.sizes - np.bitwise_count(self.bits).sum(axis=1)  # shingles that share their bit
        self.levels: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        bits, low, high, excess, span = self.bits, self.sizes, self.sizes, self.excess, LEAF
        while True:
            starts = np.arange(0, len(low), span)
            bits, low, high, excess = np.bitwise_or.reduceat(bits, starts, axis=0), np.minimum.reduceat(low, starts), np.maximum.reduceat(high, starts), np.maximum.reduceat(excess, starts)
            self.levels.append((bits, low, high, excess))
            if len(low) == 1:
                break
            span = FANOUT


class Groups:
    """Union-find over the sets of a task, started from the groups that are known."""

    def __init__(self, labels: list[int]):
        first: dict[int, int] = {}
        self.parent = [first.setdefault(x, i) for i, x in enumerate(labels)]

    def find(self, i: int) -> int:
        while self.parent[i] != i:
            self.parent[i] = self.parent[self.parent[i]]
            i = self.parent[i]
        return i

    def unite(self, i: int, j: int) -> None:
        self.parent[max(i, j)] = min(i, j)


def join_trees(sets: list[np.ndarray], labels: list[int], side: list[int], part: int, whole: int) -> list[tuple[int, int]]:
    """Links between groups. side: 0 and 1 are to be joined with each other; -1 everywhere: all with all."""
    both = side[0] != -1
    members = [[i for i in range(len(sets)) if side[i] == s] for s in (0, 1)] if both else [list(range(len(sets)))]
    if any(not m for m in members):
        return []
    width = 1 << max(8, min(15, (4 * max(map(len, sets))).bit_length()))
    trees = []
    for m in members:
        tree = Tree([sets[i] for i in m], width)
        trees.append((tree, [m[k] for k in tree.order]))
    (left, left_ids), (right, right_ids) = trees[0], trees[-1]
    groups, links = Groups(labels), []

    def leaf_members(ids: list[int], level: int, node: int) -> list[int]:
        span = LEAF * FANOUT**level
        return ids[node * span : (node + 1) * span]

    todo = [(len(left.levels) - 1, 0, len(right.levels) - 1, 0)]
    while todo:
        la, a, lb, b = todo.pop()
        if not both and la == lb and a > b:
            continue
        bits_a, low_a, high_a, excess_a = (x[a] for x in left.levels[la])
        bits_b, low_b, high_b, excess_b = (x[b] for x in right.levels[lb])
        if high_a * whole < low_b * part or high_b * whole < low_a * part:
            continue
        most = min(excess_a, excess_b) + int(np.bitwise_count(bits_a & bits_b).sum())
        if most * (part + whole) < part * (low_a + low_b):
            continue
        own_a, own_b = leaf_members(left_ids, la, a), leaf_members(right_ids, lb, b)
        roots = {groups.find(i) for i in own_a} | {groups.find(i) for i in own_b}
        if len(roots) == 1:
            continue
        if la or lb:
            downs_a = [(la - 1, c) for c in range(a * FANOUT, min((a + 1) * FANOUT, len(left.levels[la - 1][1])))] if la and la >= lb else [(la, a)]
            downs_b = [(lb - 1, c) for c in range(b * FANOUT, min((b + 1) * FANOUT, len(right.levels[lb - 1][1])))] if lb and lb >= la else [(lb, b)]
            todo += [(*x, *y) for x in reversed(downs_a) for y in reversed(downs_b)]
            continue
        rows_a, rows_b = a * LEAF, b * LEAF
        common = np.bitwise_count(left.bits[rows_a : rows_a + len(own_a), None, :] & right.bits[None, rows_b : rows_b + len(own_b), :]).sum(axis=2)
        for x, i in enumerate(own_a):
            for y, j in enumerate(own_b):
                if i == j or (not both and a == b and x >= y) or groups.find(i) == groups.find(j):
                    continue
                n, m = len(sets[i]), len(sets[j])
                most = common[x, y] + min(left.excess[rows_a + x], right.excess[rows_b + y])
                if most * (part + whole) < part * (n + m):
                    continue
                inter = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
                if whole * inter >= part * (n + m - inter):
                    groups.unite(groups.find(i), groups.find(j))
                    links.append((i, j))
    return links


def _joined(frame: pd.DataFrame, part: int, whole: int) -> pd.DataFrame:
    """Links of one task; a set that the task holds twice counts once a side."""
    frame = frame.drop_duplicates(["node", "side"])
    sets = [np.frombuffer(b, dtype="<u8") for b in frame["members"]]
    nodes = frame["node"].tolist()
    # The same node on both sides is one group already.
    found = join_trees(sets, frame["label"].tolist(), frame["side"].tolist(), part, whole) if len(sets) > 1 else []
    return pd.DataFrame({"a": [nodes[i] for i, _ in found], "b": [nodes[j] for _, j in found]}, dtype="int64")


def jaccard_components(docs: DataFrame, n: int = 3, part: int = 90, whole: int = 100) -> DataFrame:
    """(doc_id, n_shingles, place, node, component_id, component_place, component_node): component_id is the least doc_id that links reach.

    Two documents link when whole * |intersection| >= part * |union|. node and component_node are null for empty sets. place is
    xxhash64(text); component_id and component_place together name one row (or its repetitions) of the component."""
    ship(docs.sparkSession)
    before = steps()

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, classes = WordHashes(), Classes(part, whole)
        for batch in slices(batches):
            sizes, nodes, keys = [], [], []
            for text in batch.column(1).to_pylist():
                own = shingles(text, words, n)
                sizes.append(len(own))
                nodes.append(identity(own) if len(own) else None)
                keys.append(classes.keys(own) if len(own) else np.array([], dtype=np.int64))
            offsets = np.concatenate([[0], np.cumsum([len(k) for k in keys])]).astype(np.int32)
            cells = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(keys) if keys else np.array([], dtype=np.int64), pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), batch.column(2), pa.array(nodes, pa.int64()), cells], ["doc_id", "n_shingles", "place", "node", "cells"])

    # `place` finds a row again: a hash of its text; rows of one text are one node.
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("place"))
    signed = materialise(rows.mapInArrow(sign, "doc_id long, n_shingles long, place long, node long, cells array<long>"), "jaccard-signed")
    dealt = signed.where(F.col("node").isNotNull()).select("node", F.explode("cells").alias("cell"))
    shared = materialise(dealt.groupBy("cell").agg(F.min("node").alias("first"), F.max("node").alias("last")).where(F.col("first") != F.col("last")).drop("last"), "jaccard-cells")
    release(docs.sparkSession)  # the exchange of all cells, before the join's
    meeting = dealt.join(shared, "cell").where(F.col("node") != F.col("first")).select(F.col("node").alias("a"), F.col("first").alias("b"))
    branches = materialise(components(meeting, "jaccard-branches"), "jaccard-nodes")  # (node, label)
    cells, signed = signed, materialise(signed.drop("cells"), "jaccard-rows")
    discard(cells, shared)
    release(docs.sparkSession)

    # One text for each node of a branch, and its set again from that text. An id says nothing here: it may be null or repeat.
    one = F.min(F.struct("place", F.coalesce("doc_id", F.lit(NO_ID)).alias("id"))).alias("one")
    wanted = materialise(signed.where(F.col("node").isNotNull()).groupBy("node").agg(one).join(branches, "node").select("node", "label", F.col("one.place").alias("place"), F.col("one.id").alias("id")), "jaccard-wanted")
    known_nodes = wanted.count()
    few = known_nodes <= MOST_BROADCAST
    texts = rows.withColumn("id", F.coalesce("doc_id", F.lit(NO_ID))).drop("doc_id").join(F.broadcast(wanted) if few else wanted, ["place", "id"])

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, done = WordHashes(), set()
        for batch in slices(batches):
            own = [(n_, b, t) for n_, b, t in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True) if not (n_ in done or done.add(n_))]
            sets = [shingles(t, words, n) for _, _, t in own]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in own], pa.int64()), pa.array([x[1] for x in own], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["node", "branch", "members"])

    nodes = texts.select("node", F.col("label").alias("branch"), "text").mapInArrow(fetch, "node long, branch long, members binary")
    nodes = materialise(texts.select("node", F.col("label").alias("branch"), "text").mapInArrow(fetch, "node long, branch long, members binary"), "jaccard-sets")
    if nodes.count() > known_nodes:  # rows that repeat both id and text came once a task
        nodes = materialise(nodes.dropDuplicates(["node"]), "jaccard-sets-once")
    parts = materialise(branches.groupBy("label").agg(F.ceil(F.count("*") / BRANCH).cast("int").alias("parts")).withColumnRenamed("label", "branch"), "jaccard-parts")
    placed = nodes.join(parts, "branch").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    sets, placed = nodes, materialise(placed, "jaccard-placed")
    discard(sets)
    firsts = placed.where((F.col("node") == F.col("branch")) & (F.col("parts") > 1)).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    tasks = placed.unionByName(firsts).select("branch", "part", "node", F.col("node").alias("label"), F.lit(-1).alias("side"), "members")
    run = lambda frame: _joined(frame, part, whole)
    links = materialise(tasks.groupBy("branch", "part").applyInPandas(run, "a long, b long"), "jaccard-links")

    long_branch = placed.where(F.col("parts") > 1)
    if long_branch.head(1):
        known = materialise(components(links, "jaccard-known"), "jaccard-known-nodes")
        long_nodes = long_branch.join(known, "node", "left").withColumn("label", F.coalesce("label", "node"))
        long_nodes = materialise(long_nodes, "jaccard-long")
        main = materialise(long_nodes.where(F.col("node") == F.col("branch")).select("branch", F.col("label").alias("main")), "jaccard-main")
        apart = long_nodes.join(main, "branch").where(F.col("label") != F.col("main")).drop("main")
        apart = materialise(apart, "jaccard-apart")
        lanes = materialise(apart.groupBy("branch").agg(F.ceil(F.count("*") / BRANCH).cast("int").alias("lanes")), "jaccard-lanes")
        left = apart.join(lanes, "branch").withColumn("lane", F.pmod(F.xxhash64("node", F.lit(5)), F.col("lanes")).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).withColumn("side", F.lit(0))
        right = long_nodes.join(lanes, "branch").withColumn("lane", F.explode(F.sequence(F.lit(0), F.col("lanes") - 1))).withColumn("side", F.lit(1))
        pairs = left.select("branch", "lane", "part", "node", "label", "side", "members").unionByName(right.select("branch", "lane", "part", "node", "label", "side", "members"))
        more = materialise(pairs.groupBy("branch", "lane", "part").applyInPandas(run, "a long, b long"), "jaccard-more-links")
        links = links.unionByName(more)

    grouped = materialise(components(links, "jaccard-components"), "jaccard-labels")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "place")).alias("first")
    classes = materialise(signed.where(F.col("node").isNotNull()).groupBy("node").agg(first), "jaccard-classes")
    labelled = materialise(classes.join(grouped, "node", "left").withColumn("label", F.coalesce("label", "node")), "jaccard-labelled")
    least = materialise(labelled.groupBy("label").agg(F.min("first").alias("first")), "jaccard-least")
    named = labelled.drop("first").join(least, "label").select("node", F.col("first.doc_id").alias("component_id"), F.col("first.place").alias("component_place"), F.col("label").alias("component_node"))
    named = materialise(named, "jaccard-named")
    discard_since(before, signed, named)
    kept = ("doc_id", "n_shingles", "place", "node")
    out = signed.where(F.col("node").isNotNull()).select(*kept).join(named, "node").select(*kept, "component_id", "component_place", "component_node")
    none = F.lit(None).cast("long")
    blank = signed.where(F.col("node").isNull()).select(*kept, F.col("doc_id").alias("component_id"), F.col("place").alias("component_place"), none.alias("component_node"))
    return out.unionByName(blank)
