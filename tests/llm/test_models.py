"""Classifiers and the language model: held-out behaviour, brute-force counts, odd rows."""

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from sparse_neighbors.llm import maxent_lm, quality, toxicity

DOCS = "doc_id long, text string, score double, label int"


def corpus(n=240, seed=1):
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choice("aeioubcdlmnrst") for _ in range(rng.randint(2, 8))) for _ in range(300)]
    rows, labels = [], []
    for i in range(n):
        text = " ".join(rng.choice(vocabulary) for _ in range(rng.randint(20, 120))).capitalize() + "."
        good, toxic = 1, 0
        if i % 5 == 0:
            good, text = 0, text.upper().replace(" ", "!! ")
        elif i % 5 == 1:
            toxic = 1
            w = text.split()
            for _ in range(4):
                w.insert(rng.randrange(len(w)), rng.choice(["zgrukka", "zgrukko", "zgrumpf", "blarrgh"]) + rng.choice(["", "s"]))
            text = " ".join(w)
        rows.append((i, text, 0.0, 1))
        labels.append((i, good, toxic))
    return rows, labels


@pytest.fixture(scope="module")
def tables(spark):
    rows, labels = corpus()
    rows += [(900, "", 0.0, 1), (901, None, 0.0, 1), (None, "plain text", 0.0, 1), (902, "word " * 50_000, 0.0, 1), (5, rows[5][1], 0.0, 1)]
    labels += [(None, 1, 0), (3, None, None), (7, labels[7][1], labels[7][2]), (12345, 0, 1)]
    return spark.createDataFrame(rows, DOCS), spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), rows, {i: (q, t) for i, q, t in labels if q is not None}


def test_quality_on_held_out_rows(tables):
    docs, labels, rows, truth = tables
    got = quality.score_quality(docs, labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got)
    held = [r for r in got if r.held_out and r.doc_id in truth]
    assert held and all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    assert np.mean([r.predicted == truth[r.doc_id][0] for r in held]) >= 0.95
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns and kept.count() == sum(r.predicted for r in got)


def test_toxicity_on_held_out_rows(tables):
    docs, labels, rows, truth = tables
    got = toxicity.score_toxicity(docs, labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.7) for r in got)
    held = [r for r in got if r.held_out and r.doc_id in truth]
    assert held and np.mean([r.predicted == truth[r.doc_id][1] for r in held]) >= 0.9
    kept = toxicity.keep_civil(docs, labels)
    assert kept.columns == docs.columns and kept.count() == sum(not r.predicted for r in got)


class ScalarKneserNey:
    """The same model from dictionaries: rows of (class, different (word before, word) pairs of a document)."""

    def __init__(self, rows):
        self.pair = [Counter(), Counter(), Counter()]
        for label, pairs in rows:
            for x in pairs:
                self.pair[label][x] += 1
                self.pair[2][x] += 1
        self.short, self.long, self.word = ([{} for _ in range(3)] for _ in range(3))
        self.after = [{} for _ in range(3)]
        for c in range(3):
            for (before, w), n in self.pair[c].items():
                self.after[c].setdefault(before, []).append(n)
                for level, given, event in ((self.short, "", w[:3]), (self.long, w[:3], w[:6]), (self.word, w[:6], w)):
                    own = level[c].setdefault(given, Counter())
                    own[event] += 1

    def step(self, level, c, given, event, lower):
        counts = level[c].get(given)
        if not counts:
            return lower
        return (max(counts[event] - 0.75, 0) + 0.75 * len(counts) * lower) / sum(counts.values())

    def shared(self, level, given, event):
        counts = level[2].get(given)
        return self.step(level, 2, given, event, 1 / (len(counts) + 1)) if counts else 1.0

    def single(self, c, short, long, word):
        out = 1.0
        for level, given, event in ((self.short, "", short), (self.long, short, long), (self.word, long, word)):
            out *= self.step(level, c, given, event, self.shared(level, given, event))
        return out

    def paired(self, c, before, short, long, word):
        lower = self.single(c, short, long, word)
        for k in (2, c):
            after = self.after[k].get(before)
            if after:
                lower = (max(self.pair[k][before, word] - 0.75, 0) + 0.75 * len(after) * lower) / sum(after)
        return lower

    def events(self):
        """Every known word, and one unknown event beneath each known beginning."""
        for short in [*self.short[2][""], None]:
            for long in [*(self.long[2].get(short) or ()), ("long", short)]:
                for word in [*(self.word[2].get(long) or ()), ("word", long)]:
                    yield short, long, word


def pairs_of(text):
    w = [x for x in re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))]
    return list(zip([None, *w], w))


def test_toxicity_is_interpolated_kneser_ney(tables):
    docs, labels, rows, truth = tables
    model = toxicity.fit_toxicity(docs, labels)[0].value
    known = [(truth[i][1], set(pairs_of(t))) for i, t, *_ in rows if i is not None and i in truth and zlib.crc32(str(i).encode()) % 3 != 1]
    plain = ScalarKneserNey(known)
    assert len(model.pairs.rest) == len(plain.pair[2]) and model.root[2] == len(plain.pair[2])
    for c in (0, 1):
        assert math.isclose(sum(plain.single(c, *e) for e in plain.events()), 1, rel_tol=1e-9)
        for before in (None, next(iter(plain.pair[c]))[1], b"never seen"):
            assert math.isclose(sum(plain.paired(c, before, *e) for e in plain.events()), 1, rel_tol=1e-9)
    texts = [rows[1][1], rows[2][1], "unseen zgruxxx Zgrukkas words", "", None, " \n"]
    for i, j, borders, hashes in toxicity.hashed_spans(pa.array(texts), toxicity.LETTERS):
        got = model.probabilities(toxicity.words_of(borders, hashes))
        want = []
        for t in texts[i:j]:
            for before, w in pairs_of(t):
                want.append([[plain.single(c, w[:3], w[:6], w) for c in (0, 1)], [plain.paired(c, before, w[:3], w[:6], w) for c in (0, 1)]])
        assert np.allclose(got, want, rtol=1e-9)


def test_a_document_is_scored_without_its_own_counts(tables):
    docs, labels, rows, truth = tables
    model = toxicity.fit_toxicity(docs, labels)[0].value
    known = [(i, truth[i][1], t) for i, t, *_ in rows if i is not None and i in truth and zlib.crc32(str(i).encode()) % 3 != 1]
    chosen = [x for x in known if x[0] not in (3, 5)][4:6]
    for i, label, text in chosen:
        plain = ScalarKneserNey([(c, set(pairs_of(t))) for n, c, t in known if n != i])
        for _, _, borders, hashes in toxicity.hashed_spans(pa.array([text]), toxicity.LETTERS):
            n = int(borders[-1])
            got = model.probabilities(toxicity.words_of(borders, hashes), np.zeros(n, int), np.full(n, label))
        want = [[[plain.single(c, w[:3], w[:6], w) for c in (0, 1)], [plain.paired(c, p, w[:3], w[:6], w) for c in (0, 1)]] for p, w in pairs_of(text)]
        assert np.abs(np.log(got) - np.log(want)).max() < 0.05  # the root keeps a beginning that only this document had


def test_counts_are_found_by_hash():
    rng = np.random.default_rng(3)
    for n in (0, 1, 3, 5000):
        keys = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64) * np.uint64(2))
        table = rng.integers(0, 400, (len(keys), 2))
        counts = toxicity.Counts.of(keys, table[:, 0], table[:, 1])
        order = rng.permutation(len(keys))
        assert (counts.find(keys[order]) == table[order]).all()
        assert not counts.find(rng.integers(0, 1 << 63, n).astype(np.uint64) * np.uint64(2) + np.uint64(1)).any()


def test_pair_counts_reach_the_driver_in_ranges(spark, monkeypatch):
    rng = np.random.default_rng(4)
    keys = np.unique(rng.integers(-(1 << 63), 1 << 63, 3000))
    table = rng.integers(0, 400, (len(keys), 2))
    rows = spark.createDataFrame([(int(k), int(a), int(b)) for k, (a, b) in zip(keys, table, strict=True)], "pair long, n0 long, n1 long")
    sizes, whole = [], toxicity._table
    monkeypatch.setattr(toxicity, "_table", lambda *a: sizes.append(got := whole(*a)) or got)
    counts = toxicity.Counts.joined(len(keys), 2, toxicity._ranges(rows, "pair", "n0", "n1"))
    assert len(sizes) == toxicity.PARTS and max(len(x[0]) for x in sizes) < len(keys) / 4
    once = toxicity.Counts.of(keys.view(np.uint64), table[:, 0], table[:, 1])
    for name in ("borders", "rest", "columns", "large_at", "large"):
        assert (getattr(counts, name) == getattr(once, name)).all(), name
    assert (counts.find(keys.view(np.uint64)) == table).all()


def test_a_counted_pair_travels_as_two_hashes(tables, monkeypatch):
    """Pairs are shuffled and written without what their words tell, and the orders below are made from one table of words."""
    docs, labels, *_ = tables
    written, whole = {}, toxicity.materialize
    monkeypatch.setattr(toxicity, "materialize", lambda df, name: written.update({name: df.columns}) or whole(df, name))
    toxicity.fit_toxicity(docs, labels)
    assert written["counts"] == ["before", "word", "n0", "n1"] and set(written["words"]) == {"word", "long", "short", "n0", "n1", "n"}


def test_columns_of_any_name_stay(tables):
    docs, labels, *_ = tables
    from pyspark.sql import functions as F

    more = docs.withColumn("_score", F.lit("mine")).withColumn("weight", F.lit(1)).withColumn("x", F.lit(2))
    for kept in (quality.keep_good(more, labels), toxicity.keep_civil(more, labels)):
        assert kept.columns == more.columns and {r._score for r in kept.collect()} == {"mine"}


def test_without_labels_or_rows(tables):
    docs, labels, *_ = tables
    assert {r.score for r in quality.score_quality(docs, labels.where("false")).collect()} == {0.5}
    assert max(r.score for r in toxicity.score_toxicity(docs, labels.where("toxic = 0")).collect()) < 1e-6
    assert quality.score_quality(docs.where("false"), labels).count() == 0
    assert toxicity.score_toxicity(docs.where("false"), labels).count() == 0


def test_flat_trees_walk_like_a_recursion():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    trees = quality.fit_trees(x, y, np.ones(400))

    def walk(row):
        total = trees.base
        for f, t, leaf in zip(trees.feature, trees.threshold, trees.leaf, strict=True):
            node = 0
            while node < len(f):
                node = 2 * node + 1 + int(row[f[node]] > t[node])
            total += leaf[node - len(f)]
        return 1 / (1 + math.exp(-total))

    assert np.allclose(trees.score(x[:50]), [walk(r) for r in x[:50]])
    assert ((trees.score(x) > 0.5) == y).mean() > 0.97


def test_statistics_count_whole_texts(monkeypatch):
    texts = pa.array(["AB cd!! cd!! 12.\nAB cd!! cd!! 12.", None, "", "x " * 5000 + "Y" * 10])
    whole = quality.statistics(texts)
    from sparse_neighbors.llm import textscan

    monkeypatch.setattr(textscan.slices, "__defaults__", (1000,))
    cut = quality.statistics(texts)
    assert np.allclose(whole[:3], cut[:3])
    assert np.allclose(whole[3, :18], cut[3, :18], rtol=0.01)  # what spans two slices, such as a repeated word, isn't seen there
    each = [quality.statistics(pa.array([t], pa.string()))[0] for t in texts.to_pylist()]
    assert np.allclose(cut, each)  # neighbours in a batch don't matter
    assert not whole[1].any() and not whole[2].any()


def test_statistics_of_a_long_text_are_the_same_in_slices(monkeypatch):
    from sparse_neighbors.llm import textscan

    rng = random.Random(5)
    lines = [" ".join(rng.choice(["ab", "Cd!", "12"]) for _ in range(rng.randint(0, 9))) for _ in range(30)]
    mixed = "\n".join(rng.choice(lines) for _ in range(900))
    texts = ["one line of words\n" * 2000 + "short end.", mixed, "x " * 5000 + "\n" + "x " * 3000, "\n" * 4000 + "y", "a b", None, " \n" * 3000]
    whole = quality.statistics(pa.array(texts))
    assert whole[0, 20] > 0.99
    for size in (7, 100, 1000, 4097):
        monkeypatch.setattr(textscan.slices, "__defaults__", (size,))
        assert np.allclose(quality.statistics(pa.array(texts)), whole)


def words(text):
    return re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode())) + [None]


def test_base_score_and_counts_equal_brute_force(tables):
    docs, _, rows, _ = tables
    got = maxent_lm.score_texts(docs).collect()
    counts = Counter()
    for i, t, *_ in rows:
        if i is None or zlib.crc32(str(i).encode()) % 10:
            counts.update(words(t))
    n, v = sum(counts.values()), len(counts)
    want = sorted((i if i is not None else -1, len(words(t)), sum(counts[w] > 0 for w in words(t)), n, round(sum(math.log10((counts[w] + 0.1) / (n + 0.1 * (v + 1))) for w in words(t)), 5)) for i, t, *_ in rows)
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 5)) for r in got) == want
    assert all(r.score < 0 for r in got)
    held = [r for r in got if r.held_out]
    assert held and sum(r.score for r in held) > sum(r.base_score for r in held)
    assert maxent_lm.score_texts(docs.where("false")).count() == 0


def test_model_probabilities_sum_to_one():
    rng = np.random.default_rng(4)
    weights = rng.normal(size=(maxent_lm.ROWS, maxent_lm.CLASSES)).astype(np.float32)
    keys = np.concatenate([rng.integers(1 << 20, 1 << 63, 9).astype(np.uint64), [maxent_lm.END]])
    rows = maxent_lm.feature_rows(np.array([0, 10]), keys)
    assert rows.min() >= 0 and rows.max() < maxent_lm.ROWS
    p = maxent_lm.probabilities(weights, np.zeros(maxent_lm.CLASSES, np.float32), rows)
    assert np.allclose(p.sum(1), 1, atol=1e-5)
