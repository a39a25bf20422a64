"""Quality classifier: random-indexing vectors pooled for each document, then a two-layer network in numpy.

Every word and every shape of a token has an index vector, sparse and random: one signed place in each part of the vector, all
drawn by a hash. A word's context vector is the sum of the index vectors of the tokens beside it, over the whole corpus. Context
vectors live in a fixed number of rows that words are hashed to, so that what a partition sends and a worker holds does not grow
with the vocabulary: each partition adds up one dense matrix, and the matrices are summed in blocks. A document is the mean of
its tokens' context and shape vectors with a few ratios. The network learns from a bounded labelled sample, and a temperature
fitted on a part that it did not see makes its outputs probabilities.

Edge cases: null and empty texts are a vector of zeros; repeated rows score alike; without labels of both kinds every score
is 0.5; extra columns are ignored; texts and tokens of any length are read whole.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import fold, labelled_by_class, labelled_sample, materialise, one_thread, ship

#: Rows of context vectors, parts of a vector and places in each, width of the vectors, hidden units.
ROWS, PARTS, PLACES = 16_384, 4, 8
WIDTH, HIDDEN = PARTS * PLACES, 32
#: Index vectors that there are: a place and a sign for each part.
INDEXES = (2 * PLACES) ** PARTS
#: Labelled documents that are learned from, about; steps of the network's training, whatever the number of rows.
MOST_LABELLED, STEPS = 16_000, 10_000
#: Bytes of text that are split together, and tokens that are added up together.
STEP_BYTES, STEP = 6_000_000, 30_000
#: Row blocks and lanes of the matrix sum.
BLOCKS, LANES = 16, 16
RATIOS = 6


@cache
def _halves() -> np.ndarray:
    """Index vectors of half the parts: the digits of a row's number say place and sign in each part."""
    number = np.arange((2 * PLACES) ** (PARTS // 2))
    out = np.zeros((len(number), WIDTH // 2), dtype=np.float32)
    for part in range(PARTS // 2):
        digit = number // (2 * PLACES) ** part % (2 * PLACES)
        out[number, part * PLACES + digit // 2] = np.where(digit % 2, 1.0, -1.0)
    return out


def index_vectors(numbers: np.ndarray) -> np.ndarray:
    half = _halves()
    return np.hstack([half[numbers // len(half)], half[numbers % len(half)]])


def shapes(tokens: pa.Array) -> pa.Array:
    """X for a run of capitals, x for one of small letters, 9 for one of digits; other characters as they are."""
    for run, sign in (("[A-ZÀ-ÖØ-Þ]+", "X"), ("[a-zß-öø-ÿ]+", "x"), ("[0-9]+", "9")):
        tokens = pc.replace_substring_regex(tokens, run, sign)
    return tokens


def token_codes(tokens: pa.Array) -> np.ndarray:
    """Of each token: context row, number of the word's index vector and of the shape's, in one number."""
    words = pc.utf8_trim(pc.utf8_lower(tokens), ".,;:!?").cast(pa.binary()).to_numpy(zero_copy_only=False)
    hashes = np.fromiter(map(zlib.crc32, words), dtype=np.int64, count=len(words))
    forms = shapes(tokens).dictionary_encode()
    form = np.array([zlib.crc32(re.sub(r"(.)\1+", r"\1\1", f, flags=re.S).encode()) % INDEXES for f in forms.dictionary.to_pylist()], dtype=np.int64)
    return (hashes * 0x9E3779B1 >> 20) % ROWS << 32 | (hashes % INDEXES) << 16 | form[forms.indices.to_numpy()]


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Runs of documents of about STEP tokens: the slice, all tokens' codes, each document's number of tokens.

    Texts are split STEP_BYTES at a time, and each different token there is coded once."""
    for batch in batches:
        text = batch.column(batch.schema.get_field_index("text")).cast(pa.string()).fill_null("")
        size = np.cumsum(pc.binary_length(text).to_numpy(zero_copy_only=False))
        start = 0
        while start < len(text):
            end = max(start + 1, int(np.searchsorted(size, (size[start - 1] if start else 0) + STEP_BYTES, side="right")))
            lists = pc.utf8_split_whitespace(text.slice(start, end - start))
            counts = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
            known = lists.flatten().dictionary_encode()
            own = token_codes(known.dictionary)
            at = known.indices.to_numpy()
            blank = known.dictionary.index("").as_py()
            if blank >= 0:  # what lies before the first and after the last white space
                full = at != blank
                counts = np.bincount(np.repeat(np.arange(len(counts)), counts)[full], minlength=len(counts))
                at = at[full]
            upto = np.concatenate([[0], np.cumsum(counts)])
            first = 0
            while first < len(counts):
                last = max(first + 1, int(np.searchsorted(upto, upto[first] + STEP, side="right")) - 1)
                yield batch.slice(start + first, last - first), own[at[upto[first] : upto[last]]], counts[first:last]
                first = last
            start = end


def corpus_vectors(docs: DataFrame) -> np.ndarray:
    """Context vectors over every token of the corpus, rows of unit length (or 0). What reaches the driver is one fixed-size matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((ROWS, WIDTH))
        lane = 0
        for _, own, counts in _documents(batches):
            lane = (lane + int(own[:16].sum() % LANES)) % LANES
            row, near = (own >> 32).astype(np.uint16), index_vectors(own >> 16 & 0xFFFF)
            # Sums over the two tokens on each side, with gaps of zeros between documents.
            padded = np.zeros((len(own) + 2 * len(counts) + 2, WIDTH), dtype=np.float32)
            place = np.arange(len(own)) + 2 * np.repeat(np.arange(len(counts)), counts) + 2
            padded[place] = near
            near = padded[place - 1] + padded[place + 1]
            near += padded[place - 2]
            near += padded[place + 2]
            order = np.argsort(row, kind="stable")
            row = row[order]
            first = np.flatnonzero(np.diff(row.astype(np.int32), prepend=-1))
            if len(first):
                total[row[first]] += np.add.reduceat(near[order], first, axis=0)
        size = ROWS // BLOCKS
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(BLOCKS)), pa.array([lane] * BLOCKS), pa.array([total[i * size : (i + 1) * size].astype("<f4").tobytes() for i in range(BLOCKS)], pa.binary())], ["block", "lane", "sums"])

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(ROWS // BLOCKS * WIDTH)
        for b in frame["sums"]:
            total += np.frombuffer(b, dtype="<f4")
        return pd.DataFrame({"block": [frame["block"].iloc[0]], "lane": [0], "sums": [total.astype("<f4").tobytes()]})

    parts = docs.select("text").mapInArrow(run, "block long, lane long, sums binary")
    once = parts.groupBy("block", "lane").applyInPandas(add, "block long, lane long, sums binary")
    whole = once.groupBy("block").applyInPandas(add, "block long, lane long, sums binary").collect()  # BLOCKS rows
    out = np.zeros((BLOCKS, ROWS // BLOCKS * WIDTH))
    for r in whole:
        out[r["block"]] = np.frombuffer(r["sums"], dtype="<f4")
    out = out.reshape(ROWS, WIDTH)
    length = np.linalg.norm(out, axis=1, keepdims=True)
    return (out / np.where(length > 0, length, 1)).astype(np.float32)


#: Features of a document.
SIZE = 2 * WIDTH + RATIOS


def _distinct(doc: np.ndarray, code: np.ndarray, n: int) -> np.ndarray:
    """How many different codes (below 2**31) each of n documents holds."""
    both = np.sort(doc << 31 | code)
    return np.bincount(both[np.flatnonzero(np.diff(both, prepend=-1))] >> 31, minlength=n)


def pooled(codes: np.ndarray, counts: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """Mean context vector of the words, mean index vector of the shapes, and ratios, for each document."""
    shape = codes & 0xFFFF
    out = np.zeros((len(counts), SIZE), dtype=np.float32)
    full = np.flatnonzero(counts)
    if len(full):
        starts = (np.cumsum(counts) - counts)[full]
        n = counts[full]
        out[full, :WIDTH] = np.add.reduceat(vectors[codes >> 32], starts, axis=0) / n[:, None]
        out[full, WIDTH : 2 * WIDTH] = np.add.reduceat(index_vectors(shape), starts, axis=0) / n[:, None]
        doc = np.repeat(np.arange(len(counts)), counts)
        twice = np.flatnonzero((codes[1:] == codes[:-1]) & (doc[1:] == doc[:-1])) + 1
        words = _distinct(doc, codes >> 16 & 0x7FFFFFFF, len(counts))[full]
        own_shapes = _distinct(doc, shape, len(counts))[full]
        out[full, 2 * WIDTH] = np.bincount(doc[twice], minlength=len(counts))[full] / n
        out[full, 2 * WIDTH + 1] = words / n
        out[full, 2 * WIDTH + 2] = words / np.sqrt(n)
        out[full, 2 * WIDTH + 3] = own_shapes / np.sqrt(n)
        out[full, 2 * WIDTH + 4] = np.log1p(n)
        out[full, 2 * WIDTH + 5] = 1.0
    return out


@dataclass
class Net:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(((x - self.mean) / self.scale) @ self.w1 + self.b1, 0) @ self.w2 + self.b2

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -60, 60)))


def train_net(x: np.ndarray, y: np.ndarray, steps: int = STEPS, batch: int = 64, rate: float = 3e-3, decay: float = 1e-3) -> Net:
    """Adam on the log loss; the last fifth (the caller shuffles) only sets the temperature."""
    one_thread()
    rng = np.random.default_rng(7)
    mean, scale = x.mean(0), x.std(0) + 1e-3
    net = Net(mean, scale, rng.normal(0, (2 / SIZE) ** 0.5, (SIZE, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, (1 / HIDDEN) ** 0.5, HIDDEN), 0.0)
    if len(y) == 0 or y.min() == y.max():
        net.w2[:] = 0
        return net
    cut = len(y) - len(y) // 5
    z, t = (x[:cut] - mean) / scale, y[:cut]
    params = [net.w1, net.b1, net.w2, np.zeros(1)]
    first, second, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
    while step < steps:
        order = rng.permutation(cut)
        for i in range(0, min(cut, (steps - step) * batch), batch):
            own = order[i : i + batch]
            h = np.maximum(z[own] @ params[0] + params[1], 0)
            p = 1 / (1 + np.exp(-np.clip(h @ params[2] + params[3], -60, 60)))
            d = (p - t[own]) / len(own)
            dh = np.outer(d, params[2]) * (h > 0)
            grads = [z[own].T @ dh + decay * params[0], dh.sum(0), h.T @ d + decay * params[2], np.array([d.sum()])]
            step += 1
            for k, g in enumerate(grads):
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                params[k] -= rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    net.b2 = float(params[3][0])
    held, truth = net.logits(x[cut:]), y[cut:]
    if len(truth):
        choices = np.exp(np.linspace(np.log(0.5), np.log(8), 60))
        net.temperature = float(min(choices, key=lambda c: np.logaddexp(0, np.where(truth == 1, -held, held) / c).mean()))
    return net


def featured(docs: DataFrame, vectors, *keep: str) -> DataFrame:
    """The columns `keep` and x, the pooled vector."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, own, counts in _documents(batches):
            x = pooled(own, counts, vectors.value)
            yield pa.RecordBatch.from_arrays([*(part.column(part.schema.get_field_index(k)) for k in keep), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), SIZE).cast(pa.list_(pa.float32()))], [*keep, "x"])

    rows = docs.select(*keep, "text")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name in keep)
    return rows.mapInArrow(run, f"{schema}, x array<float>")


@dataclass
class Model:
    vectors: np.ndarray
    net: Net


def _fitting_rows(docs: DataFrame, sample: DataFrame, vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of the documents of a bounded sample, shuffled by a hash of the id."""
    shared = docs.sparkSession.sparkContext.broadcast(vectors)  # ROWS x WIDTH floats
    train = materialise(featured(docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id"), shared, "doc_id", "y"), "quality-train")
    rows = train.orderBy(F.xxhash64("doc_id"), "doc_id").collect()  # bounded by the sample's `most`
    return np.array([r["x"] for r in rows], dtype=np.float64).reshape(len(rows), SIZE), np.array([r["y"] for r in rows], dtype=float)


def learn(docs: DataFrame, labels: DataFrame, folds: int = 4, out: int = 2, most: int = MOST_LABELLED) -> Model:
    ship(docs.sparkSession)
    vectors = corpus_vectors(docs)
    x, y = _fitting_rows(docs, labelled_sample(labels.where(fold("doc_id", folds) != out), "quality", most), vectors)
    return Model(vectors, train_net(x, y) if len(y) else train_net(np.zeros((1, SIZE)), np.zeros(1)))


def fifths_by_class(y: np.ndarray) -> tuple[np.ndarray, int]:
    """An order whose last fifth, which train_net holds back, takes a fifth of each kind at most, and the number held back.
    The rarer kind comes first, so that it is among the rows that are fitted."""
    kinds = sorted((np.flatnonzero(y == k) for k in (0, 1)), key=len)
    cuts = [len(k) - len(k) // 5 for k in kinds]
    return np.concatenate([*(k[:c] for k, c in zip(kinds, cuts, strict=True)), *(k[c:] for k, c in zip(kinds, cuts, strict=True))]), len(y) // 5


def learn_all(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> Model | None:
    """From the labels of docs in all folds, each kind bounded by itself; None where they are of one kind.

    The kinds may be thinned unequally: the constant puts back their shares among the labels of docs."""
    ship(docs.sparkSession)
    sample, shares = labelled_by_class(labels.join(docs.select("doc_id"), "doc_id", "left_semi"), "quality", most)
    if len(shares) < 2:
        return None
    sample = materialise(sample, "quality-sample")
    vectors = corpus_vectors(docs)
    x, y = _fitting_rows(docs, sample, vectors)
    order, held = fifths_by_class(y)
    x, y = x[order], y[order]
    if len(set(y[: len(y) - held])) < 2:
        return None
    net = train_net(x, y)
    if len(set(y[len(y) - held :])) < 2:
        net.temperature = 1.0  # one kind cannot set it
    net.b2 += net.temperature * float(np.log(shares[1] / shares[0]))
    return Model(vectors, net)


def score(docs: DataFrame, model: Model, *keep: str) -> DataFrame:
    """The columns `keep` and score, one row for each row of docs."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast((model.vectors, model.net))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        vectors, net = shared.value
        for part, own, counts in _documents(batches):
            p = net(pooled(own, counts, vectors).astype(np.float64))
            yield pa.RecordBatch.from_arrays([*(part.column(part.schema.get_field_index(k)) for k in keep), pa.array(p, pa.float64())], [*keep, "score"])

    rows = docs.select(*dict.fromkeys([*keep, "text"]))
    schema = ", ".join(f"`{k}` {rows.schema[k].dataType.simpleString()}" for k in keep)
    return rows.mapInArrow(run, f"{schema}, score double")
