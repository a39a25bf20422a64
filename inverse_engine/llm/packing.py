"""Packing by multiway differencing.

A document's ids are cut into pieces: whole windows first, then a rest in at most `piece` ids each. Pieces are dealt by a
salted hash into groups of bounded size. A group's whole windows stand alone; its other pieces start as partial partitions
of k windows each, and the two partitions with the widest spread merge, largest window against smallest, until one is left.
If its largest window exceeds the capacity, k rises and the group starts again. k begins at the least possible number.

Edge cases: a null or empty text still has its end id; repeated rows are packed each on their own; null ids stay null;
an empty table gives an empty result; a very long text gives many whole windows and at most a few other pieces.
"""

from __future__ import annotations

import heapq
import json
import zlib
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import materialise, ship

#: Ids in a sequence at most; ids in a piece of a rest at most; pieces in a group, about.
CAPACITY, PIECE, GROUP = 2048, 1024, 600
#: Bytes of text that are encoded together; from so many bytes on, a run is left to `tokenizers`.
BATCH_BYTES, LONG_RUN = 4_000_000, 1000
#: Fixed value: how byte-level BPE of this family splits a text.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, deal long"


def difference(lengths: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Multiway differencing of the lengths into k windows: each item's window, and the windows' sums."""
    n = len(lengths)
    if n == 0 or k < 2:
        return np.zeros(n, dtype=np.int64), np.array([lengths.sum()] if k else [], dtype=np.int64)
    follows = np.full(n, -1, dtype=np.int64)  # a window's items form a chain
    # A partial partition: (sums, chains' heads, chains' tails) of its windows that aren't empty, sums descending.
    heap: list[tuple[int, int]] = [(-int(x), i) for i, x in enumerate(lengths)]
    heapq.heapify(heap)
    parts = {i: (np.array([x], dtype=np.int64), np.array([i]), np.array([i])) for i, x in enumerate(lengths)}
    turn = n
    while len(heap) > 1:
        (_, a), (_, b) = heapq.heappop(heap), heapq.heappop(heap)
        (sa, ha, ta), (sb, hb, tb) = parts.pop(a), parts.pop(b)
        if len(sa) < len(sb):
            (sa, ha, ta), (sb, hb, tb) = (sb, hb, tb), (sa, ha, ta)
        # The largest of b take the emptiest windows of a: those with nothing in them first.
        lone = min(k - len(sa), len(sb))
        meet = len(sb) - lone
        own = slice(0, lone)
        s, h, t = sa.copy(), ha.copy(), ta.copy()
        if meet:
            at = len(s) - 1 - np.arange(meet)
            follows[t[at]] = hb[lone:]
            t[at] = tb[lone:]
            s[at] += sb[lone:]
        s, h, t = np.concatenate([s, sb[own]]), np.concatenate([h, hb[own]]), np.concatenate([t, tb[own]])
        order = np.argsort(-s, kind="stable")
        s, h, t = s[order], h[order], t[order]
        parts[turn] = (s, h, t)
        heapq.heappush(heap, (-int(s[0] - (s[-1] if len(s) == k else 0)), turn))
        turn += 1
    s, h, _ = parts.popitem()[1]
    window = np.zeros(n, dtype=np.int64)
    for w, i in enumerate(h.tolist()):
        while i >= 0:
            window[i] = w
            i = follows[i]
    return window, s


def pack_group(lengths: np.ndarray, capacity: int) -> np.ndarray:
    """A window for each piece, numbered from 0; no window holds more than the capacity."""
    window = np.empty(len(lengths), dtype=np.int64)
    whole = np.flatnonzero(lengths == capacity)
    window[whole] = np.arange(len(whole))
    rest = np.flatnonzero(lengths < capacity)
    k = -(-int(lengths[rest].sum()) // capacity)
    while len(rest):
        own, sums = difference(lengths[rest], k)
        if sums.max() <= capacity:
            window[rest] = own + len(whole)
            break
        k += max(1, k // 200)
    return window


def _byte_of() -> dict[str, int]:
    """The byte that each letter of a byte-level vocabulary stands for: printable Latin-1 letters themselves, the others from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class Ids:
    """Ids of whole texts by a `tokenizers` file.

    Where the file is plain byte-level BPE whose ids rise with its merges, `tiktoken` gives the same ids several times faster, and is
    asked; texts with an added token in them, or with a run that its quadratic merging would take long over, go to `tokenizers`."""

    def __init__(self, path: str):
        self.path = path
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        self.added = [t["content"] for t in told.get("added_tokens") or []]
        self.fast = self._ranked(told)

    @cached_property
    def tokenizer(self):
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    @staticmethod
    def _ranked(told: dict):
        """The same vocabulary for `tiktoken`, or None."""
        import tiktoken

        model, before = told["model"], told.get("pre_tokenizer") or {}
        if told.get("normalizer") or model["type"] != "BPE" or before.get("type") != "ByteLevel" or before.get("add_prefix_space") or not before.get("use_regex", True):
            return None
        if any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "fuse_unk", "byte_fallback", "ignore_merges")):
            return None
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        order = [model["vocab"].get("".join(pair)) for pair in pairs]
        added = {t["content"] for t in told.get("added_tokens") or []}
        letters = {k: v for k, v in model["vocab"].items() if k not in added}
        if None in order or order != sorted(order) or len(letters) != 256 + len(pairs) or max(letters.values()) != 255 + len(pairs):
            return None
        byte = _byte_of()
        ranks = {bytes(byte[c] for c in token): rank for token, rank in letters.items()}
        return tiktoken.Encoding("byte-level", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

    def __call__(self, texts: pa.Array) -> list[np.ndarray]:
        lists = pc.split_pattern(texts, " ")
        parts, counts = lists.flatten(), pc.list_value_length(lists).to_numpy(zero_copy_only=False)
        slow = np.zeros(len(texts), dtype=bool)
        slow[np.repeat(np.arange(len(texts)), counts)[pc.binary_length(parts).to_numpy(zero_copy_only=False) > LONG_RUN]] = True
        for mark in [" " * LONG_RUN, *self.added]:
            slow |= pc.match_substring(texts, mark).to_numpy(zero_copy_only=False)
        out = []
        for t, s in zip(texts.to_pylist(), slow.tolist(), strict=True):
            if s or self.fast is None:
                out.append(np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, dtype="<u4"))
            else:
                out.append(self.fast.encode_to_numpy(t).astype("<u4", copy=False))
        return out


_coders: dict[str, Ids] = {}


def cut(docs: DataFrame, path: str, end_id: int = 1, capacity: int = CAPACITY, piece: int = PIECE) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, deal (a hash that spreads rows, ids repeated or not)."""
    ends = np.array([end_id], dtype="<u4")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _coders:
            _coders[path] = Ids(path)
        count = 0
        for batch in batches:
            text = batch.column(1).cast(pa.string()).fill_null("")
            size = np.cumsum(pc.binary_length(text).to_numpy(zero_copy_only=False))
            first = 0
            while first < len(text):
                last = max(first + 1, int(np.searchsorted(size, (size[first - 1] if first else 0) + BATCH_BYTES, side="right")))
                out: list[tuple] = []
                for doc, ids in zip(batch.column(0).slice(first, last - first).to_pylist(), _coders[path](text.slice(first, last - first)), strict=True):
                    ids = np.append(ids, ends)
                    n = len(ids)
                    marks = list(range(0, n - n % capacity + 1, capacity))
                    rest = n - marks[-1]
                    if rest:
                        parts = -(-rest // piece)
                        marks += [marks[-1] + rest * (j + 1) // parts for j in range(parts)]
                    for a, b in zip(marks, marks[1:], strict=False):
                        count += 1
                        out.append((doc, a, b - a, zlib.crc32(ids[a:b]), n, zlib.crc32(b"%d/%d" % (doc or 0, count))))
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "deal"])
                first = last

    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, PIECES)


def pack(docs: DataFrame, path: str, end_id: int = 1, capacity: int = CAPACITY, piece: int = PIECE, group: int = GROUP) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset), one row for each piece."""
    pieces = materialise(cut(docs, path, end_id, capacity, piece), "pieces")
    groups = max(1, -(-pieces.count() // group))

    def place(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["doc_id", "start", "deal"], kind="stable")
        window = pack_group(frame["length"].to_numpy(), capacity)
        frame["sequence_id"] = frame["grp"] * (1 << 24) + window
        frame["offset"] = frame.groupby("sequence_id")["length"].cumsum() - frame["length"]
        return frame[["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]]

    return pieces.withColumn("grp", F.pmod(F.xxhash64("deal"), F.lit(groups))).groupBy("grp").applyInPandas(
        place, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    )
