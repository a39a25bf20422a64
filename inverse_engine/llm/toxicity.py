"""Toxicity by a weighted finite-state pattern grammar.

Words become symbols: insult, threat, target, negation, reported speech, other. Four transducers (what is said, at whom,
denied or not, quoted or not) are composed once into one machine; each clause that holds an insult or a threat runs through
it, and the best path gives the clause a weight and a reading (plain, aimed, denied, quoted). A document's score is a logistic
function of its clauses' weights and readings.

Insults are learned: words, and word beginnings, whose presence in labelled toxic texts is far above that in others; one text
of each set of words counts. Targets, negations, threats and verbs of speech are the fixed lists below.

Edge cases: null and empty texts have no clause and get the lowest score; repeated rows score alike; without usable labels
no word is an insult, and the fixed weights stand; extra columns are ignored; whole texts of any length are read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from inverse_engine.llm.common import fold, labelled_sample, materialise, ship

# Closed word classes of four languages.
TARGETS = "you your yours yourself he she they them him her u ur du dich dir dein deine ihr euch er sie tu te toi ton ta vous votre il ils tú ti tu usted ustedes vosotros él ella ellos".split()
NEGATIONS = "not no never none isn't aren't wasn't don't doesn't didn't nicht kein keine nie niemals ne pas jamais aucun no nunca jamás ningún".split()
SPEECH = "said says say called calls quoted wrote reported claims claimed sagte sagt nannte schrieb berichtete dit disait appelé écrit dijo dice llamó escribió".split()
THREATS = "kill hurt destroy punch beat stab shoot burn töten umbringen schlagen vernichten tuer frapper détruire brûler matar golpear destruir quemar".split()
#: Symbols of the first tape.
OTHER, INSULT, THREAT, TARGET, NEGATION, SPEECH_VERB = range(6)
PLAIN, AIMED, DENIED, QUOTED = range(4)
READINGS = 4
#: Weights of the fixed arcs, in the logarithmic units of learned insults.
AIM_BONUS, DENIAL, QUOTATION, THREAT_WEIGHT = 1.0, -3.0, -1.5, 1.5
#: A negation reaches over so many words.
REACH = 3
#: Labelled documents that are learned from, about, and entries of the lexicon at most.
MOST_LABELLED, MOST_ENTRIES = 30_000, 20_000
WORDS = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?").findall
REMEMBERED = 400_000
FEATURES = 8


@dataclass
class Transducer:
    """Arcs (state, symbol) -> (symbol out, weight, state); weights add along a path, the greatest total wins."""

    arcs: dict[tuple, tuple]
    start: object
    final: dict = field(default_factory=dict)

    def compose(self, other: Transducer) -> Transducer:
        """What this one writes, the other reads. Both are deterministic here, and so is the result."""
        symbols = {s for _, s in self.arcs}
        start = (self.start, other.start)
        arcs, todo, seen = {}, [start], {start}
        while todo:
            a, b = todo.pop()
            for s in symbols:
                out, w1, a2 = self.arcs[a, s]
                out, w2, b2 = other.arcs[b, out]
                arcs[(a, b), s] = (out, w1 + w2, (a2, b2))
                if (a2, b2) not in seen:
                    seen.add((a2, b2))
                    todo.append((a2, b2))
        final = {(a, b): (self.final.get(a, (0.0, PLAIN))[0] + other.final.get(b, (0.0, PLAIN))[0], max(self.final.get(a, (0.0, PLAIN))[1], other.final.get(b, (0.0, PLAIN))[1])) for a, b in seen}
        return Transducer(arcs, start, final)


def grammar() -> Transducer:
    symbols = range(6)
    said = Transducer({(0, s): (s, THREAT_WEIGHT if s == THREAT else 0.0, 0) for s in symbols}, 0)
    # State: (abuse seen, target seen); both together make it aimed, in either order.
    aimed = {}
    for abuse in (0, 1):
        for target in (0, 1):
            for s in symbols:
                aimed[(abuse, target), s] = (s, 0.0, (abuse or int(s in (INSULT, THREAT)), target or int(s == TARGET)))
    whom = Transducer(aimed, (0, 0), {(1, 1): (AIM_BONUS, AIMED)})
    # State: (words that a negation still reaches, denied abuse, open abuse).
    denied = {}
    for left in range(REACH + 1):
        for no in (0, 1):
            for yes in (0, 1):
                for s in symbols:
                    abuse = s in (INSULT, THREAT)
                    hit = abuse and left > 0
                    denied[(left, no, yes), s] = (OTHER if hit else s, DENIAL if hit else 0.0, (REACH if s == NEGATION else max(0, left - 1), no or int(hit), yes or int(abuse and not hit)))
    denial = Transducer(denied, (0, 0, 0), {(left, 1, 0): (0.0, DENIED) for left in range(REACH + 1)})
    quoted = {((r, a), s): (s, QUOTATION if r and s in (INSULT, THREAT) else 0.0, (r or int(s == SPEECH_VERB), a or int(bool(r) and s in (INSULT, THREAT)))) for r in (0, 1) for a in (0, 1) for s in symbols}
    quotation = Transducer(quoted, (0, 0), {(1, 1): (0.0, QUOTED)})
    return said.compose(whom).compose(denial).compose(quotation)


class Scorer:
    """Runs texts through the grammar with a lexicon of words and word beginnings (marked by a final *)."""

    def __init__(self, lexicon: dict[str, float]):
        self.machine = grammar()
        self.words = {k: v for k, v in lexicon.items() if not k.endswith("*")}
        self.heads = {k[:-1]: v for k, v in lexicon.items() if k.endswith("*")}
        self.head_lengths = sorted({len(k) for k in self.heads})
        self.fixed = {**dict.fromkeys(TARGETS, TARGET), **dict.fromkeys(NEGATIONS, NEGATION), **dict.fromkeys(SPEECH, SPEECH_VERB), **dict.fromkeys(THREATS, THREAT)}
        self.memory: dict[str, tuple] = {}

    def symbol(self, word: str) -> tuple[int, float]:
        weight = self.words.get(word, 0.0)
        for n in self.head_lengths:
            if len(word) > n:
                weight = max(weight, self.heads.get(word[:n], 0.0))
        return (INSULT, weight) if weight else (self.fixed.get(word, OTHER), 0.0)

    def read(self, chunk: str) -> tuple[tuple[tuple[int, float], ...], bool, bool]:
        """Of a run without spaces: its symbols, whether one is abuse, whether a clause ends after it."""
        symbols = tuple(self.symbol(w) for w in WORDS(chunk))
        return symbols, any(s in (INSULT, THREAT) for s, _ in symbols), chunk[-1] in ".!?;:\n"

    def clause(self, symbols: list[tuple[int, float]]) -> tuple[float, int]:
        state, total, arcs = self.machine.start, 0.0, self.machine.arcs
        for s, w in symbols:
            out, arc, state = arcs[state, s]
            total += arc + (w if out == INSULT else 0.0)
        end, reading = self.machine.final[state]
        return total + end, reading

    def features(self, text: str | None) -> list[float]:
        parts = (text or "").lower().replace("\n", " \n ").split(" ")
        memory = self.memory
        if len(memory) > REMEMBERED:
            memory.clear()
        new = set(parts).difference(memory)
        for c in new:
            memory[c] = self.read(c) if c else ((), False, False)
        found = list(map(memory.__getitem__, parts))
        best, total, readings, threats, n_words = 0.0, 0.0, [0] * READINGS, 0, 0
        n_words = len(parts)
        done = -1
        for i, (_, abuse, _) in enumerate(found):
            if not abuse or i <= done:
                continue
            first = i
            while first > 0 and not found[first - 1][2]:
                first -= 1
            last = i
            while last < len(found) - 1 and not found[last][2]:
                last += 1
            done = last
            symbols = [s for f in found[first : last + 1] for s in f[0]]
            weight, reading = self.clause(symbols)
            best, total = max(best, weight), total + max(0.0, weight)
            readings[reading] += 1
            threats += any(s == THREAT for s, _ in symbols)
        return [best, math.log1p(total), *(math.log1p(r) for r in readings), math.log1p(threats), total / (n_words + 20)]


def _texts(batch: pa.RecordBatch, name: str) -> list[str | None]:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def _family(words: set[str]) -> int:
    """Texts of one set of words are copies."""
    return xxhash.xxh3_64_intdigest("\n".join(sorted(words))) - (1 << 63)


def learn_lexicon(train: DataFrame, most: int = MOST_ENTRIES) -> dict[str, float]:
    """Entry -> log odds. `train`: (text, y), bounded by its maker. Beginnings of four to six letters end in *."""

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [set(WORDS((t or "").lower())) for t in _texts(batch, "text")]
            yield pa.RecordBatch.from_arrays([pa.array([_family(r) for r in rows], pa.int64()), batch.column(batch.schema.get_field_index("y")).cast(pa.int32()), pa.array([list(r) for r in rows], pa.list_(pa.string()))], ["family", "y", "words"])

    def entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, list[int]] = {}
        for batch in batches:
            for y, own in zip(_texts(batch, "y"), _texts(batch, "words"), strict=True):
                keys = set(own)
                keys.update(w[:n] + "*" for w in own for n in (4, 5, 6) if len(w) > n)
                for k in keys:
                    counts.setdefault(k, [0, 0])[y] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(counts), pa.string()), pa.array([c[0] for c in counts.values()], pa.int64()), pa.array([c[1] for c in counts.values()], pa.int64())], ["entry", "clean", "toxic"])

    families = train.mapInArrow(words, "family long, y int, words array<string>").dropDuplicates(["family", "y"])
    families = materialise(families, "toxicity-families")
    n = {r["y"]: r["count"] for r in families.groupBy("y").count().collect()}
    if not n.get(1) or not n.get(0):
        return {}
    odds = F.log((F.col("toxic") + 0.25) / (n[1] + 0.5)) - F.log((F.col("clean") + 0.25) / (n[0] + 0.5))
    counted = families.mapInArrow(entries, "entry string, clean long, toxic long").groupBy("entry").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    head = F.col("entry").endswith("*")
    wanted = (F.col("toxic") >= F.when(head, 4).otherwise(2)) & (F.col("clean") <= F.col("toxic") * 0.02) & (odds > F.when(head, 3.3).otherwise(3.0))
    kept = counted.where(wanted).select("entry", odds.alias("weight")).orderBy(F.desc("weight"), "entry").limit(most)
    return {r["entry"]: float(r["weight"]) for r in kept.collect()}


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 50) -> np.ndarray:
    """Newton's method; the last weight is the constant."""
    a = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(a.shape[1])
    damp = ridge * np.eye(len(w))
    damp[-1, -1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p) + 1e-9)[:, None]).T @ a + damp, a.T @ (p - y) + damp @ w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


#: Fixed weights for when labels teach nothing: a clause's own weight decides.
UNTAUGHT = np.array([1.0, 0, 0, 0, 0, 0, 0, 0, -3.0])


def featured(docs: DataFrame, lexicon: dict[str, float], *keep: str) -> DataFrame:
    """The columns `keep` and `x`, the features of each text."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)  # at most MOST_ENTRIES entries

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value)
        for batch in batches:
            x = pa.array([scorer.features(t) for t in _texts(batch, "text")], pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(k)) for k in keep), x], [*keep, "x"])

    rows = docs.select(*keep, "text")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name in keep)
    return rows.mapInArrow(run, f"{schema}, x array<double>")


@dataclass
class Model:
    lexicon: dict[str, float]
    weights: np.ndarray


def learn(docs: DataFrame, labels: DataFrame, folds: int = 5, out: int = 0, most: int = MOST_LABELLED) -> Model:
    """From labelled documents outside the held-out fold, thinned to about `most`; two thirds teach words, the rest the weights."""
    ship(docs.sparkSession)
    sample = labelled_sample(labels.where(fold("doc_id", folds) != out), "toxic", most)
    train = materialise(docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id").select("text", "y", (F.pmod(F.xxhash64("doc_id"), F.lit(3)) < 2).alias("words")), "toxicity-train")
    lexicon = learn_lexicon(train.where("words"))
    rows = featured(train.where(~F.col("words")), lexicon, "y").collect()  # bounded by `most`
    y = np.array([r["y"] for r in rows], dtype=float)
    if not len(y) or y.min() == y.max():
        return Model(lexicon, UNTAUGHT)
    return Model(lexicon, fit_logistic(np.array([r["x"] for r in rows]), y))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted, clause_weight): one row for each row of docs."""
    ship(docs.sparkSession)
    w = [float(v) for v in model.weights]
    z = F.lit(w[-1])
    for i in range(FEATURES):
        z = z + F.col("x")[i] * w[i]
    scored = featured(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model.lexicon, "doc_id").withColumn("score", 1 / (1 + F.exp(-F.least(F.greatest(z, F.lit(-500.0)), F.lit(500.0)))))
    return scored.select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.col("x")[0].alias("clause_weight"))
