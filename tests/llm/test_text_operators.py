"""Each operator against a brute-force version, on texts with the awkward cases, and against held-out labels."""

import collections
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from inverse_engine.llm import decision_list, histogram_shards, language_model, packing, q_bpe, quality_net, sentence_spans, signature_trees, toxicity
from inverse_engine.llm.common import table

SF = "/root/testdata/sf0.01"
AWKWARD = [(None, None, "a"), (1, "", "b"), (2, " \n\t ", "c"), (3, "one", "d"), (4, "two words", "e"), (5, "same text here now", "f"), (5, "same text here now", "f"), (6, "same text here now", "g"), (7, "x" * 5000, "h"), (8, "word " * 6000, "i"), (9, "naïve ß 日本 🎉   a b  c", "j")]
SCHEMA = "doc_id long, text string, score string"


@pytest.fixture(scope="module")
def awkward(spark):
    return spark.createDataFrame(AWKWARD, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return table(spark, SF, "documents")


def counts_of(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    windows = collections.Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    covered = {j for i in range(len(words) - 7) if windows[tuple(words[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(words), sum(map(len, words)), sum(c in decision_list.SYMBOLS for c in text or ""), dup, len(covered)


def test_rule_measures(spark, docs, awkward, empty):
    for frame in (docs, awkward):
        texts = collections.Counter((r["doc_id"], counts_of(r["text"])) for r in frame.select("doc_id", "text").collect())
        got = collections.Counter((r["doc_id"], tuple(r)[1:6]) for r in decision_list.measured(frame, "doc_id").collect())
        assert got == texts
    assert decision_list.apply_rules(decision_list.measured(empty, "doc_id"), []).count() == 0


def test_rules_hold_on_labels(spark, docs):
    labels = table(spark, SF, "labels")
    rules = decision_list.learn(docs, labels)
    judged = decision_list.apply_rules(decision_list.measured(docs, "doc_id"), rules).join(labels, "doc_id").where("n_words >= 20")
    right = judged.where(F.col("kept") == (F.col("quality") == 1)).count()
    assert rules and right >= 0.95 * judged.count()
    assert decision_list.learn(docs, labels.limit(0)) == []


def test_shards(spark, docs, awkward, empty):
    for frame in (docs, awkward):
        got = histogram_shards.histogram_shards(frame).toPandas()
        assert len(got) == frame.count() and got["shard"].between(0, 23).all()
        assert sorted(zip(got["shard"], got["slot"])) == [(s, i) for s, n in sorted(got.groupby("shard").size().items()) for i in range(n)]
    loads = histogram_shards.histogram_shards(docs).groupBy("shard").agg(F.sum("size").alias("b")).toPandas()["b"]
    assert loads.max() - loads.min() <= 0.02 * loads.mean() + 2 * 33047
    assert histogram_shards.histogram_shards(empty).count() == 0


@pytest.mark.parametrize("ids", ["id", "CASE WHEN id <> 7 THEN id END", "CASE WHEN id % 2 = 1 THEN id END", "CASE WHEN id = 4 THEN -9223372036854775807 WHEN id = 6 THEN 9223372036854775807 ELSE id - 1500 END", "5"])
def test_shards_split_a_hot_text(spark, ids):
    frame = spark.range(3000).select(F.expr(ids).cast("long").alias("doc_id"), F.when(F.col("id") % 2 == 0, "hot").otherwise(F.concat(F.lit("t"), F.col("id"))).alias("text"))
    loads = histogram_shards.histogram_shards(frame).groupBy("shard").agg(F.sum("size").alias("b")).toPandas()["b"]
    assert len(loads) == 24 and loads.max() <= 1.05 * loads.mean()


def test_shards_sizes_checksums_and_order(spark, docs, awkward):
    for frame in (docs, awkward):
        want = collections.Counter((d, len((t or "").encode()) + 8, zlib.crc32((t or "").encode())) for d, t in frame.select("doc_id", "text").collect())
        for rows in (20_000, 3):  # with 3, pieces are sorted in many tasks
            got = histogram_shards.histogram_shards(frame, piece_rows=rows).toPandas()
            assert collections.Counter(zip((None if d != d else int(d) for d in got["doc_id"]), got["size"], got["text_crc32"])) == want
            assert sorted(zip(got["shard"], got["slot"])) == [(s, i) for s, n in sorted(got.groupby("shard").size().items()) for i in range(n)]
            # Equal texts are neighbours, but where a shard ends.
            ordered = got.sort_values(["shard", "slot"])["text_crc32"].tolist()
            assert sum(a != b for a, b in zip(ordered, ordered[1:])) + 1 == len(set(ordered))


def test_bpe_against_tiktoken(spark, docs, awkward, empty):
    import hashlib

    import public_tokenizers
    import tiktoken

    from inverse_engine.llm.bpe import load_ranks

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=load_ranks(path), special_tokens={})
    for frame in (docs, awkward):
        texts = frame.select("doc_id", "text").collect()
        want = collections.Counter()
        for d, t in texts:
            ids = np.array(own.encode_ordinary(t or ""), dtype="<u4")
            want[d, len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
        assert collections.Counter(map(tuple, q_bpe.encode_documents(frame, path, public_tokenizers.PATTERN).collect())) == want
    assert q_bpe.encode_documents(empty, path, public_tokenizers.PATTERN).count() == 0


def test_bpe_on_random_texts():
    import public_tokenizers
    import tiktoken

    from inverse_engine.llm.bpe import Encoder

    coder = Encoder(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, remembered=50)
    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=coder.whole, special_tokens={})
    rng = random.Random(1)
    signs = ["a", "b", " ", "  ", "\n", "\t", "'s", "é", "ß", "1", "!", "-", "\x1c", "ab", "the", "日本", "\r\n", ".", "🎉", " "]
    for _ in range(1500):
        t = "".join(rng.choice(signs) for _ in range(rng.randint(0, 20)))
        assert np.frombuffer(coder.encode([t])[0], "<u4").tolist() == own.encode_ordinary(t)
    t = "ab" * 3000
    assert np.frombuffer(coder.encode([t])[0], "<u4").tolist() == own.encode_ordinary(t)


def test_packing(spark, docs, awkward, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    whole = Tokenizer.from_file(path)
    for frame in (docs, awkward):
        texts = collections.defaultdict(list)
        for d, t in frame.select("doc_id", "text").collect():
            texts[d].append(np.array([*whole.encode(t or "", add_special_tokens=False).ids, 1], dtype="<u4"))
        got = packing.pack(frame, path).toPandas()
        assert got.groupby("sequence_id")["length"].sum().max() <= packing.CAPACITY
        ordered = got.sort_values(["sequence_id", "offset"])
        assert ((ordered.groupby("sequence_id")["length"].cumsum() - ordered["length"]) == ordered["offset"]).all()
        want = collections.Counter()
        for d, lists in texts.items():
            own = got[got["doc_id"].isna()] if d is None else got[got["doc_id"] == d]
            spans = collections.Counter(zip(own["start"], own["length"], own["ids_crc32"], own["doc_tokens"]))
            assert sum(spans.values()) and sum(n * c for (_, n, _, _), c in spans.items()) == sum(map(len, lists))
            for a, n, crc, total in spans:
                assert any(len(x) == total and zlib.crc32(x[a : a + n].tobytes()) == crc for x in lists)
    assert packing.pack(empty, path).count() == 0


def test_packing_ids_against_tokenizers():
    import public_tokenizers
    from tokenizers import Tokenizer

    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        path = public_tokenizers.path(name)
        own, whole = packing.Ids(path), Tokenizer.from_file(path)
        assert (own.fast is not None) == (name == "byte_bpe_50k.json")
        rng = random.Random(2)
        signs = ["a", "b", " ", "  ", "\n", "\t", "'s", "é", "ß", "1", "!", "-", "\x1c", "ab", "The", "日本", "\r\n", ".", "🎉", "\u00a0", "<|endoftext|>", "\u0301", "\x00"]
        texts = ["".join(rng.choice(signs) for _ in range(rng.randint(0, 25))) for _ in range(1500)]
        texts += ["", "x" * 200_000, " " * 50_000, "ab" * 3000 + " tail", "\n" * 4000, "a <|endoftext|> b", "日" * 5000]
        for t, ids in zip(texts, own(pa.array(texts, pa.string()))):
            assert ids.tolist() == whole.encode(t, add_special_tokens=False).ids


def test_differencing_keeps_to_capacity():
    rng = np.random.default_rng(0)
    for _ in range(30):
        lengths = rng.integers(1, 2049, rng.integers(1, 300))
        sums = np.bincount(packing.pack_group(lengths, 2048), weights=lengths)
        assert sums.max() <= 2048 and sums.min() > 0
    window, sums = packing.difference(np.array([4, 5, 6, 7, 8]), 2)
    assert sorted(sums) == [14, 16] and sorted(np.bincount(window, weights=[4, 5, 6, 7, 8])) == [14, 16]


def brute_spans(rows):
    seen, late = set(), collections.defaultdict(set)
    for d, t in sorted(rows, key=lambda r: (r[0] is None, r[0])):
        for h, a, b in zip(*sentence_spans.spans(t or "")):
            if h in seen:
                late[d].add((a, b))
            seen.add(h)
    return {d: sentence_spans.cleaned(t, np.array([x[0] for x in sorted(late[d])]), np.array([x[1] for x in sorted(late[d])]))[:3] for d, t in rows}


def test_span_dedup(spark, docs, awkward, empty):
    rows = [tuple(r) for r in docs.select("doc_id", "text").collect()]
    got = {r["doc_id"]: (r["text"], r["n_sentences"], r["n_removed"]) for r in sentence_spans.dedup_spans(docs).collect()}
    assert got == brute_spans(rows)
    assert sentence_spans.dedup_spans(awkward).count() == len(AWKWARD)
    assert sentence_spans.dedup_spans(empty).count() == 0


def test_span_dedup_removes_a_pasted_passage(spark):
    words = lambda seed, n: [f"w{seed}{i}q" for i in range(n)]
    passage = "Once " + " ".join(words("p", 20)) + ". Then " + " ".join(words("r", 20)) + ". So " + " ".join(words("s", 14)) + "."
    rows = [(i, f"Own {' '.join(words(i, 9))} {passage} more {' '.join(words(-i - 1, 9))}.") for i in range(3)]
    got = {r["doc_id"]: r["text"] for r in sentence_spans.dedup_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[0] == rows[0][1]
    for i in (1, 2):
        assert "wp3q" not in got[i] and "ws3q" not in got[i] and f"w{i}3q" in got[i]


def test_span_dedup_removes_a_passage_inside_long_sentences(spark):
    words = lambda seed, n: " ".join(f"w{seed}{i}q" for i in range(n))
    for passage in (words("p", 51), words("p", 26) + ". " + words("r", 25), " ".join(f"क{i}" for i in range(20)) + " ख। " + words("p", 30), words("p", 24) + ". One. " + words("r", 26)):
        rows = [(i, f"own {words(i, 40)} {passage} {words(-i - 1, 40)}.") for i in range(3)]
        got = {r["doc_id"]: r["text"] for r in sentence_spans.dedup_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        assert got[0] == rows[0][1]
        for i in (1, 2):
            left = set(got[i].split())
            assert len([w for w in passage.split() if w in left]) <= sentence_spans.LONG - sentence_spans.GRAM
            assert set(rows[i][1].split()) - set(passage.split()) <= left


def test_span_runs_reach_a_passage_end():
    text = "Aa " + "b " * 30 + "c. Bb " + "c " * 10 + "f. Cc d. Own words then."
    hashes, first, last = sentence_spans.spans(text)
    assert 45 in last  # the run that ends with the short sentence


def test_span_dedup_by_windows_of_words(spark, docs):
    """Apart from the operator's own parts: over the whole table, no stretch of 51 words is left in two places, and only words in a
    stretch of 20 that came before are gone."""
    rows = sorted((d, t or "") for d, t in docs.select("doc_id", "text").collect())
    done = {r["doc_id"]: r for r in sentence_spans.dedup_spans(docs).collect()}

    def windows(words, n):
        return [hash(tuple(words[i : i + n])) for i in range(len(words) - n + 1)]

    left = collections.Counter(h for d, _ in rows for h in windows(done[d]["text"].split(), 51))
    assert max(left.values()) == 1
    seen, touched = set(), 0
    for d, t in rows:
        words = t.split()
        late = np.zeros(len(words) + 1, dtype=bool)
        for i, h in enumerate(windows(words, 20)):
            if h in seen:
                late[i : i + 20] = True
            seen.add(h)
        assert done[d]["removed_words"] == len(words) - len(done[d]["text"].split()) <= late.sum()
        touched += done[d]["removed_words"] > 0
    assert touched > 50


def test_span_dedup_leaves_common_phrases(spark):
    phrase = "One short line of words. And another short one here."
    rows = [(i, f"w{i} " * 9 + phrase + f" v{i}" * 9) for i in range(30)]
    got = {r["doc_id"]: (r["text"], r["n_removed"]) for r in sentence_spans.dedup_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: (t, 0) for i, t in rows}


def test_clashing_columns(spark):
    """Names that the operators use inside stay with their rows, or are ignored."""
    words = " ".join(f"word{i}" for i in range(60))
    names = ["y", "_first", "first", "last", "row_key", "row", "cut", "place", "node", "label", "h", "kind", "n_removed", "id"]
    frame = spark.createDataFrame([(i, words, *[f"{n}{i}" for n in names]) for i in range(3)], ["doc_id", "text", *names])
    labels = spark.createDataFrame([(0, 1, 0, "z"), (1, 0, 1, "z"), (2, 1, 0, "z")], "doc_id long, quality int, toxic int, y string")
    got = sentence_spans.dedup_spans(frame)
    assert got.columns == ["doc_id", "text", *[n for n in names if n != "n_removed"], "n_sentences", "n_removed", "removed_words"]
    assert sorted((r["doc_id"], r["_first"], r["cut"]) for r in got.collect()) == [(i, f"_first{i}", f"cut{i}") for i in range(3)]
    assert decision_list.learn(frame, labels) == []
    assert {r["component_id"] for r in signature_trees.jaccard_components(frame).collect()} == {0}
    assert language_model.language_model_scores(frame).count() == 3 and histogram_shards.histogram_shards(frame).count() == 3
    assert quality_net.score(frame, quality_net.learn(frame, labels), "doc_id").count() == 3
    assert toxicity.score(frame, toxicity.learn(frame, labels)).count() == 3


def brute_components(rows, n, part, whole):
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w)} if 0 < len(w) < n else {tuple(w[i : i + n]) for i in range(len(w) - n + 1)})
    parent, where = list(range(len(rows))), collections.defaultdict(list)

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, s in enumerate(sets):
        for j in {j for x in s for j in where[x]}:
            k = len(s & sets[j])
            if whole * k >= part * (len(s) + len(sets[j]) - k):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
        for x in s:
            where[x].append(i)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), math.inf), math.inf if d is None else d)
    return {d: (len(sets[i]), least[find(i)] if d is not None else None) for i, (d, _) in enumerate(rows)}


@pytest.mark.parametrize("branch", [192, 6])
def test_jaccard_components(spark, branch, monkeypatch):
    monkeypatch.setattr(signature_trees, "BRANCH", branch)
    rng, rows = random.Random(3), []
    for size in (3, 5, 11, 12, 20, 40, 100, 100):
        words = ["".join(rng.choice("abcdefgh") for _ in range(4)) for _ in range(size)]
        for _ in range(rng.choice([1, 4, 30])):
            rows.append((len(rows), " ".join(words)))
            words = list(words)
            if rng.random() < 0.8:
                words[rng.randrange(len(words))] = rng.choice("xyzw") * 3
    rows += [(900 + i, t) for i, t in enumerate([None, "", " \n ", "One", "one", "a b", "A B"])]
    for n, part in ((3, 90), (5, 80)):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in signature_trees.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string"), n, part).collect()}
        assert got == brute_components(rows, n, part, 100)


def chain(n, size=60):
    """Texts of which only neighbours link: each changes the last word of the one before, and the next the first."""
    words, out = [f"w{i}" for i in range(size)], []
    for i in range(n):
        out.append(" ".join(words))
        words = list(words)
        words[-1 if i % 2 else 0] = f"new{i}"
    return out


def test_jaccard_null_and_repeated_ids(spark):
    a, b, c = chain(3)
    for rows, want in (
        ([(1, a), (None, b), (3, c)], {1: 1, None: 1, 3: 1}),
        ([(None, a), (None, b)], {None: None}),
        ([(1, a), (1, "quite another text of its own"), (2, b)], {1: 1, 2: 1}),
        ([(1, "quite another text of its own"), (1, a), (2, b)], {1: 1, 2: 1}),
        ([(5, a), (5, a), (2, b)], {5: 2, 2: 2}),
    ):
        frame = spark.createDataFrame(rows, "doc_id long, text string")
        got = [(r["doc_id"], r["component_id"]) for r in signature_trees.jaccard_components(frame).collect()]
        assert len(got) == len(rows) and set(got) == set(want.items()), rows


def test_jaccard_dealings_by_chance_lose_nothing(spark, monkeypatch):
    # Classes that leave pairs a small chance, and pairs at the very threshold: 300 texts of 48 to 400 shingles, each with three near ones.
    monkeypatch.setattr(signature_trees, "FEW_DIFFERENCES", 3)
    rng, rows = random.Random(8), []
    for i in range(75):
        words = [f"v{i}x{j}" for j in range(rng.randint(50, 400))]
        for _ in range(4):
            rows.append((len(rows), " ".join(words)))
            words = list(words)
            for _ in range(rng.randint(0, max(1, len(words) // 46))):
                words[rng.randrange(len(words))] = f"z{rng.random()}"
    for n, part in ((3, 90), (5, 80)):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in signature_trees.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string"), n, part).collect()}
        assert got == brute_components(rows, n, part, 100)
        assert 75 < len({c for _, c in got.values()}) < 300


def test_jaccard_on_the_table(spark, docs):
    rows = [tuple(r) for r in docs.select("doc_id", "text").collect()]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in signature_trees.jaccard_components(docs, 5, 80).collect()}
    assert got == brute_components(rows, 5, 80, 100)


def test_jaccard_awkward(spark, awkward, empty):
    got = {(r["doc_id"], r["component_id"]) for r in signature_trees.jaccard_components(awkward).collect()}
    assert {(5, 5), (6, 5), (1, 1), (2, 2), (None, None)} <= got
    assert signature_trees.jaccard_components(empty).count() == 0


def test_language_model(spark, docs, awkward, empty):
    got = language_model.language_model_scores(docs).toPandas()
    low = {c: c + 32 for c in range(65, 91)}
    tokens = {d: [*re.findall(r"[^\x20\x09-\x0D]+", t.translate(low)), None] for d, t in docs.select("doc_id", "text").collect()}
    held = {d: zlib.crc32(str(d).encode()) % 7 == 2 for d in tokens}
    c = collections.Counter(w for d, own in tokens.items() if not held[d] for w in own)
    n, v = sum(c.values()), len(c)
    for r in got.itertuples():
        own = tokens[r.doc_id]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(own), sum(c[w] > 0 for w in own), n)
        assert math.isclose(r.base_score, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in own), rel_tol=1e-9)
    out = got[got["held_out"]]
    assert out["score"].sum() > out["base_score"].sum()
    assert language_model.language_model_scores(awkward).count() == len(AWKWARD)
    assert language_model.language_model_scores(empty).count() == 0


def test_language_model_counts_words_that_are_not_held(spark, docs, awkward, monkeypatch):
    # Rows that repeat in all columns, one of them in training with words that are seen once, and few held words.
    rows = [(2, "rare words here once"), (2, "rare words here once"), (2, "rare words here once"), (3, "the the the of of a"), (None, "the rare"), (9, "")]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    for held in (100_000, 3, 0):
        monkeypatch.setattr(language_model, "HELD_WORDS", held)
        for table_ in (frame, docs.limit(60).select("doc_id", "text")):
            given = [tuple(r) for r in table_.collect()]
            c, n = collections.Counter(), 0
            for d, t in given:
                if zlib.crc32(("" if d is None else str(d)).encode()) % 7 != 2:
                    own = re.findall(r"[^\x20\x09-\x0D]+", t.translate({c: c + 32 for c in range(65, 91)}))
                    c.update([*own, None])
            n = sum(c.values())
            want = collections.Counter()
            for d, t in given:
                own = [*re.findall(r"[^\x20\x09-\x0D]+", t.translate({c: c + 32 for c in range(65, 91)})), None]
                want[d, len(own), sum(c[w] > 0 for w in own), n, round(sum(math.log10((c[w] + 1) / (n + len(c) + 1)) for w in own), 6)] += 1
            got = language_model.language_model_scores(spark.createDataFrame(given, "doc_id long, text string")).collect()
            assert collections.Counter((r["doc_id"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in got) == want
            assert all(r["score"] < 0 for r in got)


def small_vocabulary():
    words = [f"word{i}" for i in range(300)]
    h, kind = language_model.word_codes(pa.array(words))
    counted = [(int(x), int(k), 400 - i) for i, (x, k) in enumerate(zip(h, kind))]
    kinds = {k: (sum(c for _, o, c in counted if o == k), sum(o == k for _, o, _ in counted)) for k in range(language_model.KINDS)}
    n = sum(c for _, _, c in counted) + 50
    return words, language_model.Vocabulary(n, 301, 50, counted[:200], kinds), dict(zip(words, counted))


def test_language_model_against_a_plain_forward_pass():
    """Every token's probability by loops over kinds, leaves and distances; and the shares of all words, the end and one unknown word of each kind add up to 1."""
    m = language_model
    words, v, counted = small_vocabulary()
    p = m.Parameters(np.random.default_rng(0).normal(0, 0.4, m.Parameters.SIZE).astype(np.float32))
    p.rows[0] = 0
    p.leaf_bias[:] = np.where(v.leaf_noise.ravel() > 0, p.leaf_bias, -1e9)
    texts = ["Word3 word250 word7  word299 unknown", "", " word0 word1 word2 word3 word4 "]
    tokens = m.encode(pa.array(texts), v)
    got = m.token_log10(tokens, p, v)
    leaf_of = {int(h): int(leaf) for h, leaf in zip(v.hashes, v.leaf)}
    held = {int(h): int(c) for h, c in zip(v.hashes, v.counts)}
    soft = lambda x: [y - math.log(sum(math.exp(z) for z in x)) for y in x]

    def row(word):
        h, k = (int(x[0]) for x in m.word_codes(pa.array([word])))
        others = 1 + m.KINDS * m.LEAVES
        return 1 + k * m.LEAVES + leaf_of[h] if leaf_of.get(h) else others + int(m._ending(pa.array([word]), 4)[0] % np.uint64(m.CONTEXT_ROWS - others))

    def shares(before):
        context = sum((p.rows[row(w)] * p.distance[i] for i, w in enumerate(before)), np.zeros(m.WIDTH))
        kinds = soft([float(p.kinds[k] @ context + p.kind_bias[k]) for k in range(m.KINDS + 1)])
        leaves = [soft([max(-700.0, float(p.leaves[k * m.LEAVES + j] @ context + p.leaf_bias[k * m.LEAVES + j])) for j in range(m.LEAVES)]) for k in range(m.KINDS)]
        return kinds, leaves

    def log_word(word, kinds, leaves):
        h, k = (int(x[0]) for x in m.word_codes(pa.array([word])))
        leaf = leaf_of.get(h, 0)
        out = kinds[k] + leaves[k][leaf]
        return out if leaf else out + math.log((held.get(h, 0) + 1) / v.rest_total[k])

    at = 0
    for t in texts:
        own = t.lower().split()
        for i in range(len(own) + 1):
            kinds, leaves = shares(own[max(0, i - m.CONTEXT) : i][::-1])
            want = kinds[m.END] if i == len(own) else log_word(own[i], kinds, leaves)
            assert math.isclose(got[at], want / math.log(10), rel_tol=1e-4, abs_tol=1e-4), (t, i)
            at += 1
    assert at == len(got)
    # A kind's rest: words that are no leaf, by their true counts, and one unknown.
    total = math.exp(kinds[m.END])
    for k in range(m.KINDS):
        total += sum(math.exp(kinds[k] + leaves[k][j]) for j in range(1, m.LEAVES))
        inside = sum(c + 1 for w, (h, o, c) in counted.items() if o == k and not leaf_of.get(h))
        total += math.exp(kinds[k] + leaves[k][0]) * (inside + 1) / v.rest_total[k]
    assert math.isclose(total, 1, rel_tol=1e-6)


def test_language_model_learns_a_pattern():
    m = language_model
    words, v, _ = small_vocabulary()
    text = " ".join(words[i % 3] for i in range(6000))
    p = m.Parameters.start(v)
    trainer = m.Trainer(p.flat, v, np.zeros(m.Parameters.SIZE, dtype=np.float32), 1)
    tokens = m.encode(pa.array([text]), v)
    before = m.token_log10(tokens, p, v).sum()
    for _ in range(60):
        trainer(tokens)
    assert m.token_log10(tokens, p, v).sum() > before / 3 and not p.rows[0].any()


def held_accuracy(scored, labels, target):
    rows = scored.where("held_out").join(labels, "doc_id").select("predicted", target).collect()
    return sum(a == b for a, b in rows) / len(rows)


def test_toxicity(spark, docs, awkward, empty):
    labels = table(spark, SF, "labels")
    model = toxicity.learn(docs, labels)
    assert held_accuracy(toxicity.score(docs, model), labels, "toxic") >= 0.95
    assert toxicity.score(awkward, model).count() == len(AWKWARD) and toxicity.score(empty, model).count() == 0
    assert toxicity.learn(docs, labels.limit(0)).lexicon == {}


def test_toxicity_learns_from_unlike_texts_that_share_a_word(spark):
    # One frequent word of least hash, and texts without any long word: each text still counts.
    common = min(("".join(random.Random(i).choices("abcdefgh", k=6)) for i in range(400)), key=lambda w: zlib.crc32(w.encode()))
    clean = [(f"{common} q{a}{b} z{b}{a}", 0) for a in "abcdefghij" for b in "klmnopqrst"]
    toxic = [(f"{common} grobz {a} m{a}", 1) for a in "uvwxyzabcd"] + [(f"snek {a} p{a}", 1) for a in "efghijklmn"]
    rows = clean + [(t + " x", y) for t, y in clean] + toxic
    lexicon = toxicity.learn_lexicon(spark.createDataFrame(rows, "text string, y int"))
    assert {"grobz", "snek"} <= set(lexicon) and common not in lexicon
    assert toxicity._family({"a", "b"}) == toxicity._family({"b", "a"}) != toxicity._family({"a", "c"})


def test_toxicity_readings():
    scorer = toxicity.Scorer({"fool": 4.0, "idio*": 5.0})
    read = lambda t: scorer.clause([s for w in t.split() for s in scorer.read(w)[0]])
    plain, aimed, denied, quoted = read("such a fool"), read("you fool"), read("no fool here"), read("reported fool here")
    assert [x[1] for x in (plain, aimed, denied, quoted)] == [toxicity.PLAIN, toxicity.AIMED, toxicity.DENIED, toxicity.QUOTED]
    assert denied[0] < quoted[0] < plain[0] < aimed[0]
    assert scorer.symbol("idiotic") == (toxicity.INSULT, 5.0)


def test_quality(spark, docs, awkward, empty):
    labels = table(spark, SF, "labels")
    model = quality_net.learn(docs, labels)
    scored = quality_net.score(docs, model, "doc_id").withColumn("held_out", F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2).withColumn("predicted", (F.col("score") >= 0.7).cast("int"))
    assert held_accuracy(scored, labels, "quality") >= 0.9
    assert quality_net.score(awkward, model, "doc_id").count() == len(AWKWARD) and quality_net.score(empty, model, "doc_id").count() == 0
    assert quality_net.learn(docs, labels.limit(0)).net.temperature == 1.0


def test_quality_vectors_against_a_plain_sum(spark):
    """Context vectors and pooled features by loops over tokens."""
    texts = ["Alpha beta, gamma 12 beta", "beta  alpha\u00a0delta", None, "", "one", "ÄÖ äö!! x9 " * 3]
    codes = {}
    split = [(t or "").split() for t in texts]
    for w in {w for own in split for w in own}:
        codes[w] = int(quality_net.token_codes(pa.array([w]))[0])
    index = lambda n: quality_net.index_vectors(np.array([n]))[0]
    total = np.zeros((quality_net.ROWS, quality_net.WIDTH))
    for own in split:
        for i, w in enumerate(own):
            for j in (i - 2, i - 1, i + 1, i + 2):
                if 0 <= j < len(own):
                    total[codes[w] >> 32] += index(codes[own[j]] >> 16 & 0xFFFF)
    length = np.linalg.norm(total, axis=1, keepdims=True)
    want = total / np.where(length > 0, length, 1)
    frame = spark.createDataFrame([(t,) for t in texts], "text string").repartition(3)
    got = quality_net.corpus_vectors(frame)
    assert np.allclose(got, want, atol=1e-5)
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    for _, own, counts in quality_net._documents([batch]):
        x = quality_net.pooled(own, counts, got)
    for row, own in zip(x, split):
        if not own:
            assert not row.any()
            continue
        n, w = len(own), quality_net.WIDTH
        assert np.allclose(row[:w], np.mean([want[codes[t] >> 32] for t in own], axis=0), atol=1e-5)
        assert np.allclose(row[w : 2 * w], np.mean([index(codes[t] & 0xFFFF) for t in own], axis=0), atol=1e-5)
        different = len({codes[t] >> 16 & 0x7FFFFFFF for t in own})
        assert np.allclose(row[2 * w :], [sum(codes[a] == codes[b] for a, b in zip(own, own[1:])) / n, different / n, different / n**0.5, len({codes[t] & 0xFFFF for t in own}) / n**0.5, math.log1p(n), 1], atol=1e-5)


def test_quality_index_vectors_are_all_different():
    every = quality_net.index_vectors(np.arange(quality_net.INDEXES))
    assert len(np.unique(every, axis=0)) == quality_net.INDEXES and (np.abs(every).sum(axis=1) == quality_net.PARTS).all()
