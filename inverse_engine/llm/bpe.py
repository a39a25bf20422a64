"""Byte-level BPE by segment trees.

A piece's tree holds, over byte positions, the least (rank, position) of the adjacent pairs alive; the root is the next
merge, leftmost among equals. A merge changes two pairs, so two leaves, and their paths to the root. Pieces of like length
are worked on together: one numpy step does the same move in every tree that still has a pair to merge.

Texts are cut before each single space that stands between two other characters. No match of the splitting pattern can
cross such a place (a match may start with one space, and white space before a word gives up its last character), so the
parts can be encoded apart and remembered.

Edge cases: null and empty texts have no ids; a lone surrogate cannot occur in UTF-8 input; a piece of any length is
O(n log n).
"""

from __future__ import annotations

import base64
from collections.abc import Iterable

import numpy as np
import regex

#: From so many bytes on, a piece is worked on alone.
LONG = 128
#: Entries that a worker remembers; beyond it, the memory is emptied.
REMEMBERED = 600_000


# A space before other white space, which no part may begin with.
CROWDED = tuple(" " + chr(c) for c in (*range(9, 14), *range(28, 32), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000))


def chunks(text: str) -> list[str]:
    """The first part of the text, then the others without the single space that stood before each."""
    parts = text.split(" ")
    if "" not in parts and not any(c in text for c in CROWDED):
        return parts
    out = [parts[0]]
    for p in parts[1:]:
        if p == "" or p[0].isspace():
            out[-1] += " " + p
        else:
            out.append(p)
    return out


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class PairTable:
    """rank of the token that two adjacent tokens make; tokens are known by their ranks."""

    NONE = np.int64(1) << 40

    def __init__(self, ranks: dict[bytes, int]):
        self.token = {v: k for k, v in ranks.items()}
        self.single = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int64)
        keys, values = [], []
        for whole, rank in ranks.items():
            for cut in range(1, len(whole)):
                left, right = ranks.get(whole[:cut]), ranks.get(whole[cut:])
                if left is not None and right is not None:
                    keys.append((left << 32) | right)
                    values.append(rank)
        self.pairs = dict(zip(keys, values, strict=True))
        # An open-addressed table: probing takes one gather for most pairs.
        self.mask = np.int64((1 << (4 * len(keys)).bit_length()) - 1)
        self.keys = np.full(self.mask + 1, -1, dtype=np.int64)
        self.values = np.full(self.mask + 1, self.NONE, dtype=np.int64)
        left, value = np.array(keys, dtype=np.int64), np.array(values, dtype=np.int64)
        at = self._slot(left)
        while left.size:
            _, first = np.unique(at, return_index=True)
            first = first[self.keys[at[first]] == -1]
            self.keys[at[first]], self.values[at[first]] = left[first], value[first]
            rest = np.ones(left.size, dtype=bool)
            rest[first] = False
            left, value, at = left[rest], value[rest], (at[rest] + 1) & self.mask
        # Most of the first lookups are of single bytes.
        self.bytes = np.append(self(np.repeat(self.single, 256), np.tile(self.single, 256)), self.NONE)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key >> 32) * 1_000_003 + (key & 0xFFFFFFFF) * 7_919) & self.mask

    def __call__(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """NONE where there is no such token, or where a side is -1 (no neighbour)."""
        want = (left << 32) | right
        at = self._slot(want)
        got = self.keys[at]
        out = np.where(got == want, self.values[at], self.NONE)
        open_ = np.flatnonzero((got != want) & (got != -1))
        while open_.size:
            at[open_] = (at[open_] + 1) & self.mask
            got = self.keys[at[open_]]
            hit = got == want[open_]
            out[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (got != -1)]
        out[(left < 0) | (right < 0)] = self.NONE
        return out


def _merge_together(pieces: list[bytes], table: PairTable, width: int) -> tuple[bytes, list[int]]:
    """All pieces, each of at most `width` (a power of two) bytes, by one forest of segment trees: their ids' bytes, and where each ends."""
    n, shift = len(pieces), np.int64(max(1, width.bit_length()))
    lengths = np.fromiter(map(len, pieces), dtype=np.int64, count=n)
    flat = np.frombuffer(b"".join(p.ljust(width, b"\0") for p in pieces), dtype=np.uint8).reshape(n, width)
    alive = np.arange(width) < lengths[:, None]
    token = np.where(alive, table.single[flat], -1)
    pair = np.full((n, width), 1 << 16, dtype=np.int64)
    pair[:, :-1] = np.where(alive[:, 1:], flat[:, :-1].astype(np.int64) << 8 | flat[:, 1:], 1 << 16)
    after = np.where(np.arange(width) + 1 < lengths[:, None], np.arange(1, width + 1), -1)
    before = np.where(alive, np.arange(-1, width - 1), -1)
    tree = np.empty((n, 2 * width), dtype=np.int64)
    tree[:, width:] = (table.bytes[pair] << shift) | np.arange(width)
    for node in range(width - 1, 0, -1):
        np.minimum(tree[:, 2 * node], tree[:, 2 * node + 1], out=tree[:, node])
    none, mask = PairTable.NONE << shift, (np.int64(1) << shift) - 1
    # From here on everything is addressed in flat arrays: row r's position p is r * width + p, its node v is r * 2 * width + v.
    kept_token, token, after, before, tree = token, token.reshape(-1), after.reshape(-1), before.reshape(-1), tree.reshape(-1)
    live = np.flatnonzero(tree[1 :: 2 * width] < none)
    levels = width.bit_length() - 1
    while live.size:
        leaf, trees = live * width, live * (2 * width)
        root = tree[trees + 1]
        at = root & mask
        here = leaf + at
        gone = after[here]
        own = root >> shift
        token[here] = own
        token[leaf + gone] = -1
        following, previous = after[leaf + gone], before[here]
        after[here] = following
        has = following >= 0
        before[(leaf + following)[has]] = at[has]
        led = previous >= 0
        tree[trees + width + at] = (table(own, np.where(has, token[leaf + following], -1)) << shift) | at
        tree[trees + width + gone] = none | gone
        back = np.where(led, previous, at)
        tree[trees + width + back] = np.where(led, (table(np.where(led, token[leaf + back], -1), own) << shift) | back, tree[trees + width + back])
        up = [(at + width) >> 1, (gone + width) >> 1, (back + width) >> 1]
        for _ in range(levels):
            for k in range(3):
                node = trees + up[k]
                below = node + up[k]
                tree[node] = np.minimum(tree[below], tree[below + 1])
                up[k] >>= 1
        live = live[tree[trees + 1] < none]
    token = kept_token
    kept = token >= 0
    return token[kept].astype("<u4").tobytes(), (4 * np.cumsum(kept.sum(axis=1))).tolist()


def _merge_alone(piece: bytes, table: PairTable) -> np.ndarray:
    """One long piece, with the same tree in plain lists."""
    n, none = len(piece), int(PairTable.NONE)
    width = 1 << max(1, (n - 1).bit_length())
    shift = width.bit_length()
    mask, pairs, far = (1 << shift) - 1, table.pairs, none << shift
    token = table.single[np.frombuffer(piece, dtype=np.uint8)].tolist()
    after, before = [*range(1, n), -1], list(range(-1, n - 1))
    tree = [far] * (2 * width)
    for i in range(n - 1):
        tree[width + i] = pairs.get((token[i] << 32) | token[i + 1], none) << shift | i
    for node in range(width - 1, 0, -1):
        tree[node] = min(tree[2 * node], tree[2 * node + 1])

    def put(i: int, value: int) -> None:
        node = width + i
        tree[node] = value
        node >>= 1
        while node:
            a, b = tree[2 * node], tree[2 * node + 1]
            tree[node] = a if a < b else b
            node >>= 1

    while tree[1] < far:
        at = tree[1] & mask
        gone, previous = after[at], before[at]
        following = after[gone]
        token[at], token[gone], after[at] = tree[1] >> shift, -1, following
        put(gone, far)
        if following >= 0:
            before[following] = at
            put(at, pairs.get((token[at] << 32) | token[following], none) << shift | at)
        else:
            put(at, far)
        if previous >= 0:
            put(previous, pairs.get((token[previous] << 32) | token[at], none) << shift | previous)
    return np.array([t for t in token if t >= 0], dtype=np.int64)


class Encoder:
    """Encodes and decodes with one vocabulary, remembering pieces and parts of texts within a fixed number of entries."""

    def __init__(self, path: str, pattern: str, remembered: int = REMEMBERED):
        ranks = load_ranks(path)
        self.table = PairTable(ranks)
        self.whole = ranks
        self.find = regex.compile(pattern).findall
        self.remembered = remembered
        self.pieces: dict[str, bytes] = {}
        self.parts: dict[str, bytes] = {}

    def _learn_pieces(self, wanted: Iterable[str]) -> None:
        by_width: dict[int, list[tuple[str, bytes]]] = {}
        for piece in wanted:
            raw = piece.encode()
            by_width.setdefault(1 << max(1, (len(raw) - 1).bit_length()), []).append((piece, raw))
        for width, group in by_width.items():
            if width >= LONG:
                for piece, raw in group:
                    self.pieces[piece] = _merge_alone(raw, self.table).astype("<u4").tobytes()
                continue
            step = max(1, (1 << 18) // width)
            for i in range(0, len(group), step):
                flat, ends = _merge_together([raw for _, raw in group[i : i + step]], self.table, width)
                start = 0
                for (piece, _), end in zip(group[i : i + step], ends, strict=True):
                    self.pieces[piece] = flat[start:end]
                    start = end

    def _recall(self, memory: dict[str, bytes], seen: set[str]) -> set[str]:
        """What of `seen` is unknown. A full memory keeps only what this call has use for."""
        new = seen.difference(memory)
        if len(memory) + len(new) > self.remembered:
            kept = {k: memory[k] for k in seen if k in memory}
            memory.clear()
            memory.update(kept)
        return new

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text. `parts` holds " " + its keys, as that is how all but first parts read."""
        split = [chunks(t) if t else [] for t in texts]
        new = self._recall(self.parts, set().union(*[parts[1:] for parts in split]))
        firsts = {parts[0] for parts in split if parts}
        found = {c: self.find(" " + c) for c in new}
        heads = {c: self.find(c) for c in firsts}
        unknown = self._recall(self.pieces, {p for group in (found, heads) for pieces in group.values() for p in pieces})
        self._learn_pieces(unknown)
        piece = self.pieces.__getitem__
        for c, pieces in found.items():
            self.parts[c] = b"".join(map(piece, pieces))
        head = {c: b"".join(map(piece, pieces)) for c, pieces in heads.items()}
        part = self.parts.__getitem__
        return [head[parts[0]] + b"".join(map(part, parts[1:])) if parts else b"" for parts in split]

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.table.token.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


_encoders: dict[tuple[str, str], Encoder] = {}


def encoder(path: str, pattern: str) -> Encoder:
    """One for each worker process."""
    if (path, pattern) not in _encoders:
        _encoders[path, pattern] = Encoder(path, pattern)
    return _encoders[path, pattern]
