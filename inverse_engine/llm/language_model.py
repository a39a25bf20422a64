"""Language-model scores by a log-bilinear model, trained in numpy with noise-contrastive estimation.

Counts of all training tokens are one shuffle of hashed words. The model predicts a token in two steps: its kind (a hash of the
last letters, or the end), then, inside the kind, one of its LEAVES - 1 most frequent words or the rest; a word of the rest has
its share of the rest's add-one counts. So KINDS * (LEAVES - 1) words have an output of their own, at the price of KINDS + LEAVES
scores a token. A context is the sum of the last CONTEXT tokens' vectors, each scaled by its distance's weights; a score is the
inner product of a kind's or leaf's vector with the context, plus its bias. Every partition of the training rows goes once through
noise-contrastive steps from a common start (learned on a bounded sample), and the partitions' parameters are averaged by tokens
in a tree of sums. Scores are normalised: batched matrix products give all kinds' scores, and all leaves' of a token's kind.

The model's size is fixed, so that workers can hold it; the counts grow with the corpus. The HELD_WORDS most frequent words' counts
are held by every worker; the others meet their tokens in one join, so that every count is exact.

Edge cases: null and empty texts are one end token; a word unseen in training has count 0; without training text all
counts are 0 and every kind is alike; repeated rows are scored each; extra columns are ignored; whole texts are scored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import fold, materialise, one_thread, ship

#: Kinds of words, leaves of a kind (the first is its rest), rows of context vectors, width, context length.
KINDS, LEAVES, CONTEXT_ROWS, WIDTH, CONTEXT = 64, 64, 8192, 16, 3
END = KINDS
#: Noise kinds of a batch, noise leaves of a batch's kind, places of a kind's table of noise, tokens of a batch and of a run of neighbours in it, rate of learning.
NOISE_KINDS, NOISE_LEAVES, TABLE, BATCH, RUN, RATE = 24, 12, 1024, 8192, 128, 0.15
#: Tokens of the common start, about, and characters of a text there at most; steps that its squared gradients count for.
START_TOKENS, START_CHARS, START_STEPS = 400_000, 20_000, 100
#: Words whose counts every worker holds, at most; bytes of text that are split together.
HELD_WORDS, STEP_BYTES = 100_000, 4_000_000
LANES, BLOCKS = 16, 16


def split(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Different words, lower-cased (A-Z); of all words their places among those; each text's number of words.

    Arrow's ASCII white space is the six characters that separate words."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(texts))
    counts = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
    known = lists.flatten().dictionary_encode()
    at, blank = known.indices.to_numpy(), known.dictionary.index("").as_py()
    if blank >= 0:  # what lies before the first and after the last white space
        full = at != blank
        counts = np.bincount(np.repeat(np.arange(len(counts)), counts)[full], minlength=len(counts))
        at = at[full]
    return known.dictionary, at, counts


def _hashed(values: pa.Array) -> np.ndarray:
    raw = values.cast(pa.binary()).to_numpy(zero_copy_only=False)
    return np.fromiter(map(xxhash.xxh3_64_intdigest, raw), dtype=np.uint64, count=len(raw))


def _ending(words: pa.Array, letters: int) -> np.ndarray:
    """Hashes of the last bytes of each word without closing marks."""
    ends = pc.binary_slice(pc.utf8_rtrim(words, ".,;:!?").cast(pa.binary()), -letters).dictionary_encode()
    return _hashed(ends.dictionary)[ends.indices.to_numpy()]


def word_codes(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash (as a signed long) and kind of each word."""
    return _hashed(words).view(np.int64), (_ending(words, 3) % np.uint64(KINDS)).astype(np.int32)


def _pieces(batches: Iterator[pa.RecordBatch], name: str) -> Iterator[tuple[pa.RecordBatch, pa.Array]]:
    """Slices of about STEP_BYTES of text, and their texts without nulls."""
    for batch in batches:
        text = batch.column(batch.schema.get_field_index(name)).cast(pa.string()).fill_null("")
        size = np.cumsum(pc.binary_length(text).to_numpy(zero_copy_only=False))
        start = 0
        while start < len(text):
            end = max(start + 1, int(np.searchsorted(size, (size[start - 1] if start else 0) + STEP_BYTES, side="right")))
            yield batch.slice(start, end - start), text.slice(start, end - start)
            start = end


def token_counts(train: DataFrame) -> DataFrame:
    """(h, kind, c): counts of all words, added up within each slice of text and by Spark before the exchange."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, text in _pieces(batches, "text"):
            words, at, _ = split(text)
            h, kind = word_codes(words)
            c = np.bincount(at, minlength=len(h))
            yield pa.RecordBatch.from_arrays([pa.array(x[c > 0]) for x in (h, kind, c.astype(np.int64))], ["h", "kind", "c"])

    return train.select("text").mapInArrow(run, "h long, kind int, c long").groupBy("h", "kind").agg(F.sum("c").alias("c"))


class Vocabulary:
    """What every worker holds: totals, the leaves' words, and the counts of the most frequent words, in order of their hashes."""

    def __init__(self, n: int, v: int, ends: int, held: list[tuple[int, int, int]], kinds: dict[int, tuple[int, int]]):
        self.n, self.v, self.ends = n, v, ends
        #: Tokens and words of each kind beside its leaves' words; one unknown word is added to each.
        inside = np.zeros((KINDS, 2))
        for k, of_kind in kinds.items():
            inside[k] = of_kind
        leaf_counts = np.zeros((KINDS, LEAVES))
        used = [1] * KINDS
        leaf = np.zeros(len(held), dtype=np.int64)
        for i, (_, k, c) in enumerate(held):  # by descending count
            if used[k] < LEAVES:
                leaf[i], leaf_counts[k, used[k]] = used[k], c
                inside[k] -= (c, 1)
                used[k] += 1
        self.rest_total = inside.sum(axis=1) + 1
        leaf_counts[:, 0] = self.rest_total
        kind_counts = np.append(leaf_counts.sum(axis=1), ends + 1.0)
        self.kind_noise = kind_counts / kind_counts.sum()
        self.leaf_noise = leaf_counts / leaf_counts.sum(axis=1, keepdims=True)
        order = np.argsort([h for h, _, _ in held], kind="stable")
        self.hashes = np.array([h for h, _, _ in held], dtype=np.int64)[order]
        self.counts = np.array([c for _, _, c in held], dtype=np.int64)[order]
        self.leaf = leaf[order]

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Counts (-1 where not held) and leaves of words."""
        if not len(self.hashes):
            return np.full(len(h), -1), np.zeros(len(h), dtype=np.int64)
        at = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        hit = self.hashes[at] == h
        return np.where(hit, self.counts[at], -1), np.where(hit, self.leaf[at], 0)


class Parameters:
    """context vectors (the first row stays zero), distance weights, vectors and biases of kinds and leaves, as views of one array."""

    SHAPES = ((CONTEXT_ROWS, WIDTH), (CONTEXT, WIDTH), (KINDS + 1, WIDTH), (KINDS + 1,), (KINDS * LEAVES, WIDTH), (KINDS * LEAVES,))
    SIZE = sum(int(np.prod(s)) for s in SHAPES)

    def __init__(self, flat: np.ndarray):
        self.flat = flat
        views, at = [], 0
        for s in self.SHAPES:
            views.append(flat[at : at + int(np.prod(s))].reshape(s))
            at += int(np.prod(s))
        self.rows, self.distance, self.kinds, self.kind_bias, self.leaves, self.leaf_bias = views

    @classmethod
    def start(cls, vocabulary: Vocabulary) -> Parameters:
        rng = np.random.default_rng(11)
        out = cls(rng.normal(0, 0.1, cls.SIZE).astype(np.float32))
        out.rows[0] = 0.0
        out.distance[:] = 1.0
        out.kind_bias[:] = np.log(vocabulary.kind_noise)
        # A leaf without a word has no share.
        out.leaf_bias[:] = np.where(vocabulary.leaf_noise > 0, np.log(np.maximum(vocabulary.leaf_noise, 1e-30)), -1e9).ravel()
        return out

    def contexts(self, rows: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Contexts of runs of neighbouring tokens, and the vectors that they are sums of. rows: (runs, CONTEXT + length) context rows,
        CONTEXT tokens before each run's first included; place: (runs, length) places in their texts, beyond whose beginning nothing counts."""
        vectors, length = self.rows[rows], place.shape[1]
        out = np.zeros((*place.shape, WIDTH), dtype=np.float32)
        for i in range(CONTEXT):
            out += vectors[:, CONTEXT - 1 - i : CONTEXT - 1 - i + length] * self.distance[i] * (place > i)[:, :, None]
        return out, vectors


def encode(texts: pa.Array, vocabulary: Vocabulary) -> dict[str, np.ndarray]:
    """Of every token: kind, leaf (numbered over all kinds), place in its text, count (-1 if not held), hash; ends are kind END.
    row: context rows, CONTEXT more at the beginning; lengths: each text's number of tokens."""
    words, at, counts = split(texts)
    h, kind = word_codes(words)
    count, leaf = vocabulary.find(h)
    number = kind.astype(np.int64) * LEAVES + leaf
    others = 1 + KINDS * LEAVES
    row = np.where(leaf > 0, 1 + number, others + (_ending(words, 4) % np.uint64(CONTEXT_ROWS - others)).astype(np.int64))
    lengths = counts + 1
    upto = np.cumsum(lengths)
    n = int(upto[-1]) if len(upto) else 0
    inside = np.ones(n, dtype=bool)
    inside[upto - 1] = False
    out = {"kind": np.full(n, END), "leaf": np.zeros(n, dtype=np.int64), "count": np.full(n, vocabulary.ends), "h": np.zeros(n, dtype=np.int64), "lengths": lengths}
    for name, values in (("kind", kind), ("leaf", number), ("count", count), ("h", h)):
        out[name][inside] = values[at]
    out["row"] = np.zeros(CONTEXT + n, dtype=np.int64)
    out["row"][CONTEXT:][inside] = row[at]
    out["place"] = np.arange(n) - np.repeat(upto - lengths, lengths)
    return out


def _sums(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys (below 2**16), and the sums of their rows."""
    order = np.argsort(keys.astype(np.uint16), kind="stable")
    own = keys[order]
    first = np.flatnonzero(np.diff(own, prepend=-1))
    return own[first], np.add.reduceat(values[order], first, axis=0)


class Trainer:
    """Noise-contrastive steps on parameters that it owns; `squares` are sums of squared gradients."""

    def __init__(self, flat: np.ndarray, vocabulary: Vocabulary, squares: np.ndarray, seed: int):
        self.p, self.seen, self.steps = Parameters(flat), Parameters(squares), 0
        self.random = np.random.default_rng(seed)
        self.kind_noise = vocabulary.kind_noise
        self.log_kind = np.log(NOISE_KINDS * vocabulary.kind_noise).astype(np.float32)
        self.log_leaf = np.log(np.maximum(NOISE_LEAVES * vocabulary.leaf_noise, 1e-30)).astype(np.float32).ravel()
        # Places of a kind's table are dealt to its leaves by their shares.
        shares = (np.arange(TABLE) + 0.5) / TABLE
        self.table = np.array([np.minimum(np.searchsorted(np.cumsum(q), shares), np.flatnonzero(q)[-1]) + k * LEAVES for k, q in enumerate(vocabulary.leaf_noise)])

    @staticmethod
    def _move(values: np.ndarray, squares: np.ndarray, where, gradient: np.ndarray) -> None:
        squares[where] += gradient * gradient
        values[where] -= RATE * gradient / np.sqrt(squares[where] + 1e-6)

    def __call__(self, tokens: dict[str, np.ndarray]) -> None:
        """One pass over the tokens, in batches of runs of neighbours that are drawn without order."""
        n = len(tokens["kind"])
        starts = np.arange(0, n - RUN + 1, RUN)
        for start in range(0, len(starts), BATCH // RUN):
            if start == 0:
                self.random.shuffle(starts)
            own = starts[start : start + BATCH // RUN, None]
            self._step(tokens, own + np.arange(RUN), own + np.arange(CONTEXT + RUN))
        if n % RUN:  # what is left at the end is a run of its own
            rest = np.arange(n - n % RUN, n)[None]
            self._step(tokens, rest, np.append(rest, rest[0, -1] + 1 + np.arange(CONTEXT))[None])

    def _step(self, tokens: dict[str, np.ndarray], at: np.ndarray, around: np.ndarray) -> None:
        """One batch: places of its tokens, and of the context rows around its runs."""
        p, seen = self.p, self.seen
        n = np.float32(at.size)
        rows, place = tokens["row"][around], tokens["place"][at]
        context, before = p.contexts(rows, place)
        # From here to the context rows, tokens are in order of their kinds.
        kind = tokens["kind"][at.ravel()].astype(np.uint8)
        order = np.argsort(kind, kind="stable")
        kind, leaf = kind[order], tokens["leaf"][at.ravel()[order]]
        wide = np.empty((len(kind), WIDTH + 1), dtype=np.float32)
        wide[:, :WIDTH], wide[:, WIDTH] = context.reshape(-1, WIDTH)[order], 1
        context = wide[:, :WIDTH]
        edges = np.searchsorted(kind, np.arange(KINDS + 2))
        here = np.flatnonzero(np.diff(edges))
        # Kinds: the batch shares its noise.
        false = self.random.choice(KINDS + 1, NOISE_KINDS, p=self.kind_noise)
        true_vectors, false_vectors = p.kinds[kind], p.kinds[false]
        true_score = np.einsum("nw,nw->n", context, true_vectors) + (p.kind_bias - self.log_kind)[kind]
        d_true = -1 / (1 + np.exp(np.clip(true_score, -30, 30)))
        d_false = 1 / (1 + np.exp(-np.clip(context @ false_vectors.T + (p.kind_bias - self.log_kind)[false], -30, 30)))
        d_context = d_true[:, None] * true_vectors + d_false @ false_vectors
        d_kind = np.zeros((KINDS + 1, WIDTH + 1), dtype=np.float32)
        d_kind[here] = np.add.reduceat(d_true[:, None] * wide, edges[here], axis=0)
        np.add.at(d_kind, false, d_false.T @ wide)
        # Leaves: the words of a kind share noise of that kind.
        upto = int(edges[END])
        d_leaf = np.zeros((KINDS * LEAVES, WIDTH + 1), dtype=np.float32)
        offset = p.leaf_bias - self.log_leaf
        noise = self.table[np.arange(KINDS)[:, None], self.random.integers(0, TABLE, (KINDS, NOISE_LEAVES))]
        spans = [(k, int(edges[k]), int(edges[k + 1]), p.leaves[noise[k]]) for k in here.tolist() if k < END]
        scores = np.empty((upto, NOISE_LEAVES), dtype=np.float32)
        for k, a, b, vectors in spans:
            scores[a:b] = context[a:b] @ vectors.T + offset[noise[k]]
        d = 1 / (1 + np.exp(-np.clip(scores, -30, 30)))
        for k, a, b, vectors in spans:
            d_context[a:b] += d[a:b] @ vectors
            np.add.at(d_leaf, noise[k], d[a:b].T @ wide[a:b])
        own = leaf[:upto]
        vectors = p.leaves[own]
        d_own = -1 / (1 + np.exp(np.clip(np.einsum("nw,nw->n", context[:upto], vectors) + offset[own], -30, 30)))
        d_context[:upto] += d_own[:, None] * vectors
        if upto:
            which, sums = _sums(own, d_own[:, None] * wide[:upto])
            d_leaf[which] += sums
            which = np.union1d(which, noise[here[here < END]])
            self._move(p.leaves, seen.leaves, which, d_leaf[which, :WIDTH] / n)
            self._move(p.leaf_bias, seen.leaf_bias, which, d_leaf[which, WIDTH] / n)
        back = np.empty((*at.shape, WIDTH), dtype=np.float32)
        back.reshape(-1, WIDTH)[order] = d_context / n
        d_rows, d_distance = np.zeros_like(before), np.zeros_like(p.distance)
        for i in range(CONTEXT):
            own = back * (place > i)[:, :, None]
            span = slice(CONTEXT - 1 - i, CONTEXT - 1 - i + at.shape[1])
            d_distance[i] = np.einsum("rlw,rlw->w", own, before[:, span])
            d_rows[:, span] += own * p.distance[i]
        which, sums = _sums(rows.ravel(), d_rows.reshape(-1, WIDTH))
        real = which > 0  # an end's row stays zero
        self._move(p.rows, seen.rows, which[real], sums[real])
        self._move(p.distance, seen.distance, slice(None), d_distance)
        self._move(p.kinds, seen.kinds, slice(None), d_kind[:, :WIDTH] / n)
        self._move(p.kind_bias, seen.kind_bias, slice(None), d_kind[:, WIDTH] / n)
        self.steps += 1


def _common_start(train: DataFrame, vocabulary: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """Parameters fitted on a bounded sample: rows by a hash of id and text, equal texts once, a window of each at most. Beside them,
    squared gradients scaled to START_STEPS steps, so that the corpus, not the sample, has the say."""
    share = max(1, vocabulary.n // START_TOKENS)
    picked = train.where(F.pmod(F.xxhash64("doc_id", "text", F.lit(23)), F.lit(share)) == 0)
    begin = F.pmod(F.xxhash64("text"), F.greatest(F.length("text") - START_CHARS, F.lit(0)) + 1).cast("int") + 1
    window = picked.select(F.substring("text", begin, F.lit(START_CHARS)).alias("text")).distinct()
    sample = [r["text"] for r in window.orderBy(F.xxhash64("text")).collect()]  # about START_TOKENS words
    p, squares = Parameters.start(vocabulary), np.zeros(Parameters.SIZE, dtype=np.float32)
    trainer = Trainer(p.flat, vocabulary, squares, 5)
    tokens = encode(pa.array(sample, pa.string()), vocabulary)
    while len(sample) and trainer.steps < 8 * START_TOKENS // BATCH:
        trainer(tokens)
    return p.flat, squares * np.float32(min(1.0, START_STEPS / max(1, trainer.steps)))


def train_parameters(train: DataFrame, vocabulary: Vocabulary) -> np.ndarray:
    """One pass over all training rows. What reaches the driver is BLOCKS rows of averaged parameters, and the start's sample."""
    one_thread()
    start = _common_start(train, vocabulary)
    shared = train.sparkSession.sparkContext.broadcast((vocabulary, *start))
    size = -(-Parameters.SIZE // BLOCKS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        own, flat, squares = shared.value
        trainer, weight = Trainer(flat.copy(), own, squares.copy(), 3), 0
        for _, text in _pieces(batches, "text"):
            tokens = encode(text, own)
            trainer(tokens)
            weight += len(tokens["kind"])
        if weight:
            padded = np.pad(trainer.p.flat, (0, size * BLOCKS - Parameters.SIZE)).reshape(BLOCKS, size)
            lane = [weight % LANES] * BLOCKS
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(BLOCKS)), pa.array(lane, pa.int64()), pa.array([float(weight)] * BLOCKS), pa.array([x.tobytes() for x in padded], pa.binary())], ["block", "lane", "weight", "mean"])

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        sums = np.zeros(size)
        for w, b in zip(frame["weight"], frame["mean"], strict=True):
            sums += w * np.frombuffer(b, dtype="<f4")
        total = frame["weight"].sum()
        return pd.DataFrame({"block": [frame["block"].iloc[0]], "lane": [0], "weight": [total], "mean": [(sums / total).astype("<f4").tobytes()]})

    schema = "block long, lane long, weight double, mean binary"
    parts = train.select("text").mapInArrow(run, schema).groupBy("block", "lane").applyInPandas(add, schema).groupBy("block").applyInPandas(add, schema).collect()
    if not parts:
        return start[0]
    return np.concatenate([np.frombuffer(r["mean"], dtype="<f4") for r in sorted(parts, key=lambda r: r["block"])])[: Parameters.SIZE].copy()


def _log_share(scores: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    """Natural log of the chosen rows' shares under a softmax of each column."""
    scores -= scores.max(axis=0)
    own = scores[chosen, np.arange(scores.shape[1])].astype(np.float64)
    np.exp(scores, out=scores)
    return own - np.log(scores.sum(axis=0))


def token_log10(tokens: dict[str, np.ndarray], p: Parameters, vocabulary: Vocabulary) -> np.ndarray:
    """log10 probability of every token. A word of a kind's rest takes count 0 where its count is not held."""
    out = np.empty(len(tokens["kind"]))
    leaves, biases = p.leaves.reshape(KINDS, LEAVES, WIDTH), p.leaf_bias.reshape(KINDS, LEAVES)
    for start in range(0, len(out), 2 * BATCH):
        s = slice(start, start + 2 * BATCH)
        kind, leaf = tokens["kind"][s], tokens["leaf"][s]
        context = p.contexts(tokens["row"][None, start : start + CONTEXT + len(kind)], tokens["place"][None, s])[0][0]
        log = _log_share(p.kinds @ context.T + p.kind_bias[:, None], kind)
        order = np.argsort(kind.astype(np.uint8), kind="stable")
        context, slot = context[order], leaf[order] % LEAVES
        edges = np.searchsorted(kind[order], np.arange(KINDS + 1))
        for k in np.flatnonzero(np.diff(edges)):
            a, b = edges[k], edges[k + 1]
            log[order[a:b]] += _log_share(leaves[k] @ context[a:b].T + biases[k][:, None], slot[a:b])
        out[s] = log / np.log(10)
    rest = (tokens["kind"] < END) & (tokens["leaf"] % LEAVES == 0)
    out[rest] += np.log10(np.maximum(tokens["count"][rest], 0) + 1.0) - np.log10(vocabulary.rest_total)[tokens["kind"][rest]]
    return out


def language_model_scores(docs: DataFrame, folds: int = 7, out: int = 2) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score), one row for each row of docs."""
    ship(docs.sparkSession)
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    train = rows.where(fold("doc_id", folds) != out)
    ends = train.count()
    counts = materialise(token_counts(train), "word-counts")
    kinds = {r["kind"]: (r["c"], r["v"]) for r in counts.groupBy("kind").agg(F.sum("c").alias("c"), F.count("*").alias("v")).collect()}  # KINDS rows
    # The lowest count that keeps the held words within their bound, from powers of two.
    by_size = {r["b"]: r["v"] for r in counts.groupBy(F.floor(F.log2("c")).alias("b")).agg(F.count("*").alias("v")).collect()}  # 63 rows at most
    cut, sum_ = 62, 0
    for b in sorted(by_size, reverse=True):
        if sum_ + by_size[b] > HELD_WORDS:
            break
        cut, sum_ = b, sum_ + by_size[b]
    least = 1 << cut
    held = sorted(((r["h"], r["kind"], r["c"]) for r in counts.where(F.col("c") >= least).collect()), key=lambda x: (-x[2], x[0]))  # HELD_WORDS at most
    n = ends + sum(c for c, _ in kinds.values())
    v = (1 if ends else 0) + sum(w for _, w in kinds.values())
    vocabulary = Vocabulary(n, v, ends, held, kinds)
    flat = train_parameters(train, vocabulary)
    shared = spark.sparkContext.broadcast((vocabulary, flat))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one_thread()
        own, values = shared.value
        p, log_base = Parameters(values), np.log10(own.n + own.v + 1)
        number = TaskContext.get().partitionId() << 40  # a number for each row, which nothing else says where rows repeat
        for part, text in _pieces(batches, "text"):
            tokens = encode(text, own)
            count, lengths = tokens["count"], tokens["lengths"]
            model = token_log10(tokens, p, own)
            base = np.log10(np.maximum(count, 0) + 1.0) - log_base
            starts = np.cumsum(lengths) - lengths
            open_ = count < 0
            per_doc = np.add.reduceat(open_.astype(np.int64), starts)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(per_doc)]).astype(np.int32), pa.int32()), pa.array(tokens["h"][open_], pa.int64()))
            yield pa.RecordBatch.from_arrays(
                [pa.array(number + np.arange(len(lengths))), part.column(0), pa.array(lengths), pa.array(np.add.reduceat((count > 0).astype(np.int64), starts)), pa.array(np.add.reduceat(base, starts)), pa.array(np.add.reduceat(model, starts)), lists],
                ["row", "doc_id", "n_tokens", "known", "base", "model", "open"],
            )
            number += len(lengths)

    scored = materialise(rows.mapInArrow(run, "row long, doc_id long, n_tokens long, known long, base double, model double, open array<long>"), "lm-scored")
    # Rare words meet their counts by one exchange; a word that is not held has few rows by definition.
    rare = scored.select("row", F.explode("open").alias("h"))
    met = rare.join(counts.where(F.col("c") < least).select("h", "c"), "h")
    sums = met.groupBy("row").agg(F.sum(F.log10(F.col("c") + 1)).alias("more"), F.count("*").alias("more_known"))
    joined = scored.drop("open").join(sums, "row", "left")
    more, known = F.coalesce("more", F.lit(0.0)), F.coalesce("more_known", F.lit(0))
    return joined.select(
        "doc_id",
        (fold("doc_id", folds) == out).alias("held_out"),
        "n_tokens",
        (F.col("known") + known).cast("long").alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + more).alias("base_score"),
        (F.col("model") + more).alias("score"),
    )
