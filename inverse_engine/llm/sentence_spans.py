"""Substring deduplication by sliding sentence spans.

A text is cut into sentences at closing marks, line ends, and before a capitalised word that no mark precedes (passages are
pasted into the middle of sentences). From each sentence on, and back from each, the shortest run of at least LEAST_SENTENCES
sentences and LEAST_WORDS words is hashed: shorter ones are common phrases, which clean documents share. Stretches of LONG words that hold no such run inside (long sentences, other scripts)
choose the run of GRAM words with the least hash among theirs: two documents that share the stretch choose alike, so every
common stretch of LONG words holds a common run, and at most LONG - GRAM words at its two ends are outside its runs.
Runs that occur more than once in the corpus are joined back, and the words under an occurrence other than the
first (by doc_id, then place) are removed.

Edge cases: null and empty texts have no sentence and stay; texts below the least run are never cut; rows that agree in id
and text count as one document and get the same result; null ids come last in the order of occurrences; extra columns stay
with their rows; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from inverse_engine.llm.common import materialise, release, ship

LEAST_SENTENCES, LEAST_WORDS = 2, 20
#: Words of a common stretch that may not pass unseen ("over 50"), and of the runs that such stretches choose.
LONG, GRAM = 51, 40
LAST = (1 << 63) - 1
#: The end of a sentence: a mark with its white space, a line end, or white space between a word and a capitalised one.
_end = re.compile(r"(?<=[.!?…])[\"'”»)]*\s+|\s*\n\s*|(?<=\w)\s+(?=[A-ZÀ-ÖØ-Þ][^A-ZÀ-ÖØ-Þ])")


def bounds(text: str) -> list[tuple[int, int]]:
    """(begin, end) of each sentence with the white space after it: together they are the text."""
    if not text:
        return []
    ends = [m.end() for m in _end.finditer(text)]
    if not ends or ends[-1] != len(text):
        ends.append(len(text))
    return list(zip([0, *ends[:-1]], ends, strict=True))


#: Odd, so that its powers have inverses modulo 2 ** 64.
_BASE = 0x9E3779B97F4A7C15


@cache
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of _BASE and of its inverse, modulo 2 ** 64."""
    bases = np.ones((2, n), dtype=np.uint64)
    bases[0, 1:], bases[1, 1:] = _BASE, pow(_BASE, -1, 1 << 64)
    return tuple(np.cumprod(bases, axis=1, dtype=np.uint64))


def _chosen_grams(words: list[bytes], bare: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each stretch of LONG words that begins at one of `bare`, the run of GRAM words with the least hash: hashes, first words."""
    size = 1 << len(words).bit_length()  # few sizes to remember
    power, inverse = _powers(size)
    own = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))
    sums = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(own * power[: len(own)], dtype=np.uint64)])
    h = (sums[GRAM:] - sums[:-GRAM]) * inverse[: len(own) - GRAM + 1]
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    first = np.unique(bare + np.lib.stride_tricks.sliding_window_view(h, LONG - GRAM + 1)[bare].argmin(axis=1))
    return h[first].view(np.int64), first


def spans(text: str) -> tuple[list[int], list[int], list[int]]:
    """Hash, first and last word of each run. White space does not count in the hash."""
    sentences = [text[a:b].split() for a, b in bounds(text)]
    words = np.fromiter(map(len, sentences), dtype=np.int64, count=len(sentences))
    if words.sum() < LEAST_WORDS:
        return [], [], []
    joined = [" ".join(s).encode() for s in sentences]
    total = np.concatenate([[0], np.cumsum(words)])
    place = np.arange(len(words))
    last = np.maximum(np.searchsorted(total, total[:-1] + LEAST_WORDS) - 1, place + LEAST_SENTENCES - 1)
    ahead = (last < len(words)) & (words > 0)
    first = np.minimum(np.searchsorted(total, total[1:] - LEAST_WORDS, side="right") - 1, place - LEAST_SENTENCES + 1)
    back = (first >= 0) & (words > 0)
    runs = np.unique(np.concatenate([place[ahead] * len(words) + last[ahead], first[back] * len(words) + place[back]]))
    first, last = runs // len(words), runs % len(words)
    hashes = [xxhash.xxh3_64_intdigest(b"\n".join(joined[i : j + 1])) - (1 << 63) for i, j in zip(first.tolist(), last.tolist(), strict=True)]
    begin, end = total[first], total[last + 1]
    n = int(total[-1])
    if n >= LONG:
        # The least end of the runs that begin at a word or later. A run at a stretch's very border does not count: what is beyond differs.
        least = np.full(n + 1, n + LONG)
        np.minimum.at(least, begin, end)
        least = np.minimum.accumulate(least[::-1])[::-1]
        bare = np.flatnonzero(least[1 : n - LONG + 2] > np.arange(n - LONG + 1) + LONG - 1)
        if len(bare):
            more, start = _chosen_grams(b" ".join(joined).split(b" ") if words.all() else b" ".join(j for j in joined if j).split(b" "), bare)
            return hashes + more.tolist(), [*begin.tolist(), *start.tolist()], [*(end - 1).tolist(), *(start + GRAM - 1).tolist()]
    return hashes, begin.tolist(), (end - 1).tolist()


def cleaned(text: str | None, first: np.ndarray | None, last: np.ndarray | None) -> tuple[str | None, int, int, int]:
    """The text without the words of the given runs; numbers of sentences, of those that lost words, of words removed."""
    if text is None:
        return None, 0, 0, 0
    own = bounds(text)
    if first is None or len(first) == 0:
        return text, len(own), 0, 0
    begins = [m.start() for m in re.finditer(r"\S+", text)]
    change = np.zeros(len(begins) + 1, dtype=np.int64)
    np.add.at(change, np.asarray(first), 1)
    np.add.at(change, np.asarray(last) + 1, -1)
    gone = np.cumsum(change[:-1]) > 0
    kept = text[: begins[0]] + "".join(text[a:b] for a, b, g in zip(begins, [*begins[1:], len(text)], gone.tolist(), strict=True) if not g)
    sentence = np.searchsorted([b for _, b in own], np.asarray(begins)[gone], side="right")
    return kept, len(own), len(np.unique(sentence)), int(gone.sum())


def _row_key() -> Column:
    return F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.coalesce(F.col("text"), F.lit("")))


def repeated_runs(docs: DataFrame) -> DataFrame:
    """(row_key, first, last): per document, the runs that are not the first occurrence."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [spans(t) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array([f[k] for f in found], pa.list_(kind)) for k, kind in enumerate((pa.int64(), pa.int32(), pa.int32())))], ["row_key", "place", "hashes", "firsts", "lasts"])

    ship(docs.sparkSession)
    rows = docs.where(F.col("text").isNotNull()).select(_row_key().alias("row_key"), F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("place"), "text")
    found = materialise(rows.mapInArrow(run, "row_key long, place long, hashes array<long>, firsts array<int>, lasts array<int>"), "sentence-runs")
    runs = found.select("row_key", "place", F.explode(F.arrays_zip("hashes", "firsts", "lasts")).alias("r")).select("row_key", "place", F.col("r.hashes").alias("h"), F.col("r.firsts").alias("first"), F.col("r.lasts").alias("last"))
    # Partial sums before the exchange make a frequent run one row for each task.
    seen = runs.groupBy("h").agg(F.min(F.struct("place", "first", "row_key")).alias("origin"), F.count("*").alias("times")).where("times > 1")
    # Written first, so that both sides of the join have an exchange and a frequent run's rows can be split.
    again = materialise(seen.select("h", F.col("origin.row_key").alias("origin_key"), F.col("origin.first").alias("origin_first")), "repeated-runs")
    release(docs.sparkSession)  # the exchange of all runs, before the join's
    late = runs.join(again, "h").where((F.col("row_key") != F.col("origin_key")) | (F.col("first") != F.col("origin_first")))
    return late.select("row_key", "first", "last").groupBy("row_key").agg(F.collect_set(F.struct("first", "last")).alias("runs")).select("row_key", F.col("runs.first").alias("first"), F.col("runs.last").alias("last"))


def dedup_spans(docs: DataFrame) -> DataFrame:
    """docs with `text` cut, and n_sentences, n_removed, removed_words beside it."""

    @pandas_udf("kept string, n_sentences int, n_removed int, removed_words int")
    def cut(text, first, last):
        import pandas as pd

        done = [cleaned(t, a, b) for t, a, b in zip(text, first, last, strict=True)]
        return pd.DataFrame(done, columns=["kept", "n_sentences", "n_removed", "removed_words"])

    # The rows' own columns stay in one struct, so that no name of theirs meets one of these.
    marked = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), _row_key().alias("row_key")).join(repeated_runs(docs), "row_key", "left")
    done = marked.withColumn("cut", cut(F.col("row").getField("text"), "first", "last"))
    names = [c for c in docs.columns if c not in ("n_sentences", "n_removed", "removed_words")]
    return done.select(*[F.col("cut.kept").alias("text") if c == "text" else F.col("row").getField(c).alias(c) for c in names], "cut.n_sentences", "cut.n_removed", "cut.removed_words")
