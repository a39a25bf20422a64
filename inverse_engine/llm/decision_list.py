"""Quality rules: a decision list learned by sequential covering, run as one Spark conditional expression.

Measures of a text are built-in functions only. A bounded sample of labelled documents is counted by binned measures; a rule
is grown on part of the counts (the threshold with the best information gain joins the conjunction), pruned on the others
(trailing conditions go while that raises precision), and kept if it is precise there; what it covers leaves the counts. The list
becomes CASE WHEN ... END.

Edge cases: a null or empty text has no words, all measures are 0 and it fails the base rule; repeated rows are judged each;
without usable labels the list is empty and keeps all; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import GAP, labelled_sample, materialise

#: Words of a window whose repetition counts.
WINDOW = 8
#: The characters that count as symbols.
SYMBOLS = "#*$%&|<>"
#: Ratios that rules may test.
MEASURES = ["symbol_share", "repeat_share", "dup_line_share", "upper_share", "digit_share", "word_length", "distinct_share", "mark_share", "words_a_line"]
#: Labelled documents that are learned from, about; candidate thresholds for a measure; rules and conditions at most.
MOST_LABELLED, THRESHOLDS, MOST_RULES, MOST_CONDITIONS = 20_000, 16, 12, 3


def _without(text: Column, characters: str) -> Column:
    return F.translate(text, characters, "")


def measured(docs: DataFrame, *keep: str) -> DataFrame:
    """The columns `keep`, the five counts of the contract and MEASURES, in three projections without any shuffle."""
    text = F.coalesce(F.col("text"), F.lit(""))
    first = docs.select(
        *keep,
        text.alias("t"),
        F.array_remove(F.split(text, GAP), "").alias("w"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
    )
    second = first.select(
        *keep,
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        (F.length("t") - F.length(_without(F.col("t"), SYMBOLS))).cast("long").alias("n_symbols"),
        F.size("lines").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        (F.length("t") - F.length(_without(F.col("t"), "ABCDEFGHIJKLMNOPQRSTUVWXYZÄÖÜÉÈÊÇÑÍÓÁÚ"))).alias("n_upper"),
        (F.length("t") - F.length(_without(F.col("t"), "0123456789"))).alias("n_digits"),
        (F.length("t") - F.length(_without(F.col("t"), "!?:;=_/\\{}[]()~^+@\""))).alias("n_marks"),
        F.transform("w", lambda x: F.xxhash64(x)).alias("h"),
    )
    at = F.sequence(F.lit(0), F.col("n_words").cast("int") - WINDOW)
    windows = F.when(F.col("n_words") >= WINDOW, F.transform(at, lambda i: F.xxhash64(*[F.get("h", i + k) for k in range(WINDOW)])))
    third = second.withColumn("win", windows).withColumn("distinct_words", F.size(F.array_distinct("h"))).drop("h")
    # Windows that occur twice: sort (hash, place), keep those equal to a neighbour, and count the words under their places.
    repeated = F.size("win") > F.size(F.array_distinct("win"))
    placed = F.when(repeated, F.array_sort(F.transform("win", lambda x, i: F.struct(x.alias("x"), i.alias("i")))))
    fourth = third.withColumn("placed", placed).drop("win")
    alike = F.filter("placed", lambda s, j: (s["x"] == F.get("placed", j - 1)["x"]) | (s["x"] == F.get("placed", j + 1)["x"]))
    fifth = fourth.withColumn("places", F.when(F.col("placed").isNotNull(), F.array_sort(F.transform(alike, lambda s: s["i"])))).drop("placed")
    spread = F.zip_with("places", F.slice("places", F.lit(2), F.greatest(F.size("places"), F.lit(1))), lambda a, b: F.least(F.lit(WINDOW), b - a))
    words = F.greatest(F.col("n_words"), F.lit(1))
    chars = F.greatest(F.col("word_chars"), F.lit(1))
    return fifth.withColumn("n_repeat_words", F.coalesce(F.aggregate(spread, F.lit(0).cast("long"), lambda total, x: total + x), F.lit(0).cast("long"))).select(
        *keep,
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        (F.col("n_symbols") / words).alias("symbol_share"),
        (F.col("n_repeat_words") / words).alias("repeat_share"),
        (F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1))).alias("dup_line_share"),
        (F.col("n_upper") / chars).alias("upper_share"),
        (F.col("n_digits") / chars).alias("digit_share"),
        (F.col("word_chars") / words).alias("word_length"),
        (F.col("distinct_words") / words).alias("distinct_share"),
        (F.col("n_marks") / words).alias("mark_share"),
        (F.col("n_words") / F.greatest(F.col("n_lines"), F.lit(1))).alias("words_a_line"),
    )


@dataclass(frozen=True)
class Rule:
    """If all conditions (measure, at least?, threshold) hold, the document is of the rejected class."""

    conditions: tuple[tuple[str, bool, float], ...]
    covered: int
    precision: float

    def column(self) -> Column:
        out = F.lit(True)
        for name, at_least, value in self.conditions:
            out = out & ((F.col(name) >= value) if at_least else (F.col(name) < value))
        return out


def cover(bins: np.ndarray, y: np.ndarray, weight: np.ndarray, grow: np.ndarray, cuts: list[list[float]], least_precision: float = 0.9, least_cover: int = 5) -> list[Rule]:
    """Sequential covering over counted cells: `bins` has each cell's bin by measure, y is 1 for the class to keep."""
    tests = [(m, up, b) for m in range(bins.shape[1]) for b in range(1, len(cuts[m]) + 1) for up in (True, False)]
    holds = np.array([(bins[:, m] >= b) if up else (bins[:, m] < b) for m, up, b in tests]) if tests else np.zeros((0, len(y)), dtype=bool)
    bad = np.where(y == 0, weight, 0.0)
    good = np.where(y == 1, weight, 0.0)
    left = np.ones(len(y), dtype=bool)
    rules: list[Rule] = []

    def precision(mask: np.ndarray, part: np.ndarray) -> tuple[float, float]:
        p, n = bad[mask & part].sum(), good[mask & part].sum()
        return (p + 0.5) / (p + n + 1), p

    while len(rules) < MOST_RULES and bad[left & grow].sum() >= least_cover:
        mask, chosen = left.copy(), []
        while len(chosen) < MOST_CONDITIONS:
            now = mask & grow
            p0, n0 = bad[now].sum(), good[now].sum()
            if n0 == 0 or p0 == 0:
                break
            p, n = holds[:, now] @ bad[now], holds[:, now] @ good[now]
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = np.where(p > 0, p * (np.log2(p / (p + n)) - np.log2(p0 / (p0 + n0))), -np.inf)
            best = int(np.argmax(gain))
            if not gain[best] > 1e-9:
                break
            chosen.append(best)
            mask &= holds[best]
        # Pruning: the shortest beginning of the conjunction that is as precise on the other part.
        def begin(k: int) -> np.ndarray:
            return np.logical_and.reduce([left, *holds[chosen[:k]]])

        if not chosen:
            break
        scores = [precision(begin(k), ~grow)[0] for k in range(1, len(chosen) + 1)]
        keep = next(k for k, s in enumerate(scores, 1) if s >= max(scores) - 0.005)
        mask = begin(keep)
        sure, p = precision(mask, ~grow)
        if sure < least_precision or bad[mask & grow].sum() < least_cover:
            break
        rules.append(Rule(tuple((MEASURES[tests[t][0]], tests[t][1], cuts[tests[t][0]][tests[t][2] - 1]) for t in chosen[:keep]), int(bad[mask].sum()), float(sure)))
        left &= ~mask
    return rules


def learn(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> list[Rule]:
    """Rules from about `most` labelled documents; what reaches the driver is counts of binned measures, bounded by that sample."""
    sample = labelled_sample(labels, "quality", most)
    rows = materialise(measured(docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id"), "doc_id", "y"), "rule-measures").where(F.col("n_words") >= 20)
    share = [i / THRESHOLDS for i in range(1, THRESHOLDS)] + [0.97, 0.99]
    found = rows.agg(*[F.percentile_approx(m, share, 2000).alias(m) for m in MEASURES]).first()
    cuts = [sorted({float(x) for x in found[m] or []}) for m in MEASURES]
    # Measures that are mostly 0 also need thresholds among their other values.
    other = rows.agg(*[F.percentile_approx(F.when(F.col(m) > 0, F.col(m)), [0.02, 0.1, 0.25, 0.5, 0.75], 2000).alias(m) for m in MEASURES]).first()
    cuts = [sorted({*c, *(float(x) for x in other[m] or [])} - {0.0}) for c, m in zip(cuts, MEASURES, strict=True)]
    binned = [sum([(F.col(m) >= x).cast("int") for x in c], F.lit(0)).alias(m) for m, c in zip(MEASURES, cuts, strict=True)]
    cells = rows.select(*binned, "y", (F.pmod(F.xxhash64("doc_id"), F.lit(3)) < 2).alias("grow")).groupBy(*MEASURES, "y", "grow").count().collect()
    if not cells:
        return []
    return cover(np.array([r[: len(MEASURES)] for r in cells]), np.array([r["y"] for r in cells]), np.array([r["count"] for r in cells], dtype=float), np.array([r["grow"] for r in cells]), cuts)


def apply_rules(frame: DataFrame, rules: list[Rule]) -> DataFrame:
    """Adds base_failed, rule (1-based place of the rule that rejects, else null) and kept."""
    which = F.lit(None).cast("int")
    for i, rule in reversed(list(enumerate(rules, 1))):
        which = F.when(rule.column(), F.lit(i)).otherwise(which)
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    return frame.withColumn("base_failed", base).withColumn("rule", which).withColumn("kept", ~F.col("base_failed") & F.col("rule").isNull())
