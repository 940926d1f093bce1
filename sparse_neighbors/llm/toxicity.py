"""Toxicity by class-conditional Kneser-Ney models.

For each class a word's probability is interpolated over two orders. The pair order counts in how many documents the word follows
the one before it. The order below has continuation counts: after how many different words a word was seen. It is a chain
of a word's first LETTERS[1] bytes, its first LETTERS[0] bytes given these, and the word given those, so that a stem speaks for a word
that was seldom or never seen. Every count of a class gives up DISCOUNT; what is freed goes to the same event's counts over both
classes together, and what those free to the next order. So a rare expression differs between the classes only as far as what
it shares with others does, and each model sums to 1 over words.

The length-normalised log-likelihoods of the two classes are compared at both orders: over the whole text, and over the windows
of WINDOWS words where they differ most, as a long text dilutes a short passage. A logistic regression weighs these; each
training document is scored without its own counts.

Only labelled documents, SAMPLE of each class at most, are learned from; every count of theirs is kept, down to what a
single document holds, as sorted hashes with small integers, which are broadcast once. Results for odd input: a null or empty
text has no evidence and the score of zeros; without labels of both classes the score is 0; a null doc_id is scored and never
held out; rows that repeat are scored alike; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .labelled import remainder, sample_texts
from .shared import collect_garbage, discard, materialize, prepare_workers
from .textscan import hashed_spans, mix64

SAMPLE = {1: 8_000, 0: 12_000}
LETTERS = (6, 3)
DISCOUNT = 0.75
BOTH = 2
LARGE = 255
PARTS = 8  # ranges of keys in which the pairs' counts reach the driver, a power of two
WINDOWS = (12, 1)
FEATURES = 1 + 2 * (1 + len(WINDOWS))


@dataclass
class Words:
    """Hashes of every word of some texts: its first bytes, itself, the word before it, both together."""

    short: np.ndarray
    long: np.ndarray
    word: np.ndarray
    before: np.ndarray
    pair: np.ndarray


def words_of(borders: np.ndarray, hashes: list[np.ndarray]) -> Words:
    """The word before a text's first word is a border mark."""
    word, long, short = hashes
    before = np.concatenate([[0], word[:-1]]).astype(np.uint64)
    before[borders[:-1][np.diff(borders) > 0]] = 1
    before = mix64(before * np.uint64(0x9FB21C651E98DF25) + np.uint64(77))
    return Words(mix64(short + np.uint64(1)), mix64(long + np.uint64(2)), word, before, pair_hash(before, word))


def pair_hash(before: np.ndarray, word: np.ndarray) -> np.ndarray:
    return mix64(before + word * np.uint64(0xC2B2AE3D27D4EB4F))


@dataclass
class Counts:
    """Of one order: 32 bits of each key in the order of keys, the border of each run of equal leading bits, and columns of counts.

    Counts take a byte; a row with one of LARGE or more is kept apart in full. Leading and kept bits tell keys apart: of n keys,
    about 32 + log2(n / 4) bits.
    """

    bits: int
    borders: np.ndarray
    rest: np.ndarray
    columns: np.ndarray
    large_at: np.ndarray
    large: np.ndarray

    @staticmethod
    def of(keys: np.ndarray, *columns: np.ndarray) -> Counts:
        return Counts.joined(len(keys), len(columns), [(keys, *columns)])

    @staticmethod
    def joined(n: int, width: int, parts: Iterable[tuple[np.ndarray, ...]]) -> Counts:
        """Of n keys that come in parts, each above the one before it; one part is in hand at once."""
        bits = max(1, n.bit_length() - 2)
        borders, rest, kept = np.zeros((1 << bits) + 1, np.uint32), np.empty(n, np.uint32), np.empty((n, width), np.uint8)
        large_at, large, at = [np.zeros(0, np.int64)], [np.zeros((0, width), np.int32)], 0
        for keys, *columns in parts:
            order = np.argsort(keys)
            keys, table = keys[order], np.stack(columns, 1)[order]
            borders += np.searchsorted(keys >> np.uint64(64 - bits), np.arange((1 << bits) + 1, dtype=np.uint64)).astype(np.uint32)
            rest[at : at + len(keys)] = (keys >> np.uint64(32 - bits)).astype(np.uint32)
            kept[at : at + len(keys)] = np.minimum(table, LARGE)
            own = np.flatnonzero(table.max(1, initial=0) >= LARGE)
            large_at.append(at + own)
            large.append(table[own])
            at += len(keys)
        if at != n:
            raise ValueError(f"{at} keys came instead of {n}")
        return Counts(bits, borders, rest, kept, np.concatenate(large_at), np.concatenate(large))

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Rows of the keys, zeros for a key that isn't there."""
        out = np.zeros((len(keys), self.columns.shape[1]))
        if not len(self.rest) or not len(keys):
            return out
        run, wanted = (keys >> np.uint64(64 - self.bits)).astype(np.int64), (keys >> np.uint64(32 - self.bits)).astype(np.uint32)
        at, end = self.borders[run].astype(np.int64), self.borders[run + 1].astype(np.int64)
        open_ = np.flatnonzero(at < end)
        while len(open_):  # as often as the longest run, some 20 times
            here = at[open_]
            same = self.rest[here] == wanted[open_]
            hit, rows = open_[same], here[same]
            out[hit] = self.columns[rows]
            if len(self.large_at):
                where = np.minimum(np.searchsorted(self.large_at, rows), len(self.large_at) - 1)
                big = self.large_at[where] == rows
                out[hit[big]] = self.large[where[big]]
            open_ = open_[~same]
            at[open_] += 1
            open_ = open_[at[open_] < end[open_]]
        return out


def own_counts(owner: np.ndarray, given: np.ndarray, event: np.ndarray, single: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each word: different events that its document has after the word's context, and those that are `single`."""
    order = np.lexsort((event, given, owner))
    context = np.ones(len(order), bool)
    context[1:] = (given[order][1:] != given[order][:-1]) | (owner[order][1:] != owner[order][:-1])
    first = context.copy()
    first[1:] |= event[order][1:] != event[order][:-1]
    group = np.cumsum(context) - 1
    out = np.empty((2, len(order)))
    for x, values in zip(out, (first, first & single[order]), strict=True):
        x[order] = np.bincount(group, values)[group] if len(order) else 0
    return out[0], out[1]


def discounted(count: np.ndarray, kinds: np.ndarray, total: np.ndarray, lower: np.ndarray) -> np.ndarray:
    """Discounted relative count, and what the discounts freed times the lower order; the lower order alone without a count."""
    freed = np.maximum(count - DISCOUNT, 0) + DISCOUNT * kinds * lower
    return np.where(total > 0, np.minimum(freed / np.maximum(total, 1), 1), lower)


@dataclass
class Toxicity:
    """Counts have a column for class 0, class 1 and both together (BOTH); where kinds of what follows are counted, three more for these."""

    pairs: Counts  # documents, without the column for both
    before: Counts  # documents summed over pairs; different words after
    words: Counts  # different words before
    long: Counts  # the same, summed over words; different words
    short: Counts  # the same, summed over words; different long beginnings
    root: np.ndarray  # the same, summed over words; different short beginnings
    weights: np.ndarray

    def probabilities(self, x: Words, owner: np.ndarray | None = None, own: np.ndarray | None = None) -> np.ndarray:
        """P(word) and P(word | word before), in each class (words x order x class). With `owner`, each word's document, and `own`, the class whose counts hold it: without these."""
        pair, before, word, long, short = self.pairs.find(x.pair) @ np.array([[1, 0, 1], [0, 1, 1]]), self.before.find(x.before), self.words.find(x.word), self.long.find(x.long), self.short.find(x.short)
        root = np.broadcast_to(self.root.astype(float), (len(x.word), 6))
        if owner is not None:
            at = np.arange(len(own))
            for column in (own, BOTH):
                alone = pair[at, column] <= 1
                events, lost = own_counts(owner, x.before, x.pair, alone)
                pair[at, column] -= 1
                before[at, column] -= events
                before[at, 3 + column] -= lost
                for counts, name in ((word, x.word), (long, x.long), (short, x.short)):
                    counts[at, column] -= own_counts(owner, name, x.pair, alone)[1]
                long[at, 3 + column] -= own_counts(owner, x.long, x.word, word[at, column] <= 0)[1]
                short[at, 3 + column] -= own_counts(owner, x.short, x.long, long[at, column] <= 0)[1]
            for counts in (pair, before, word, long, short):
                np.maximum(counts, 0, out=counts)
        chain = ((root, short), (short, long), (long, word))
        shared = []
        for given, event in chain:  # an event that neither class has seen counts as one kind more
            unseen = 1 / (given[:, 3 + BOTH] + 1)
            shared.append(np.where(given[:, BOTH] > 0, discounted(event[:, BOTH], given[:, 3 + BOTH], given[:, BOTH], unseen), 1))
        out = np.empty((len(x.word), 2, 2))
        for c in (0, 1):
            single = np.ones(len(x.word))
            for (given, event), lower in zip(chain, shared, strict=True):
                single = single * discounted(event[:, c], given[:, 3 + c], given[:, c], lower)
            either = discounted(pair[:, BOTH], before[:, 3 + BOTH], before[:, BOTH], single)
            out[:, 0, c] = single
            out[:, 1, c] = discounted(pair[:, c], before[:, 3 + c], before[:, c], either)
        return out

    def features(self, borders: np.ndarray, x: Words, own: np.ndarray | None = None) -> np.ndarray:
        """`own`: the class of each text, where its counts are in the model."""
        owner = None if own is None else np.repeat(np.arange(len(own)), np.diff(borders))
        p = np.log(self.probabilities(x, owner, None if own is None else own[owner]))
        out = np.zeros((len(borders) - 1, FEATURES))
        out[:, 0] = 1
        size = np.diff(borders)
        some, ends = np.flatnonzero(size), np.repeat(borders[1:], size)
        if not len(some):
            return out
        f = 1
        for order in (0, 1):
            sums = np.concatenate([[0], np.cumsum(p[:, order, 1] - p[:, order, 0])])
            out[some, f] = (sums[borders[1:]] - sums[borders[:-1]])[some] / size[some]
            for n in WINDOWS:
                f += 1
                windows = (sums[np.minimum(np.arange(len(p)) + n, ends)] - sums[:-1]) / n
                out[some, f] = np.maximum.reduceat(windows, borders[:-1][some])
            f += 1
        return out

    def score(self, text: pa.Array) -> np.ndarray:
        out = np.zeros(len(text))
        for i, j, borders, hashes in hashed_spans(text, LETTERS):
            x = self.features(borders, words_of(borders, hashes))
            out[i:j] = 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))
        return out


def nothing(weights: np.ndarray) -> Toxicity:
    empty = [Counts.of(np.zeros(0, np.uint64), *np.zeros((n, 0))) for n in (2, 6, 3, 6, 6)]
    return Toxicity(*empty, np.zeros(6), weights)


def _pairs(batches):
    """Each document's different pairs, once."""
    for batch in batches:
        labels = np.asarray(batch.column("label"))
        for i, j, borders, hashes in hashed_spans(batch.column("text"), LETTERS):
            x = words_of(borders, hashes)
            owner = np.repeat(np.arange(j - i), np.diff(borders))
            order = np.lexsort((x.pair, owner))
            first = np.ones(len(order), bool)
            first[1:] = (x.pair[order][1:] != x.pair[order][:-1]) | (owner[order][1:] != owner[order][:-1])
            at = order[first]
            columns = [pa.array(v[at].view(np.int64)) for v in (x.before, x.word)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(labels[i + owner[at]].astype(np.int32))], ["before", "word", "label"])


def _names(batches):
    """The words of each slice of texts, once, with their beginnings."""
    for batch in batches:
        for _, _, borders, hashes in hashed_spans(batch.column("text"), LETTERS):
            x = words_of(borders, hashes)
            at = np.unique(x.word, return_index=True)[1]
            yield pa.RecordBatch.from_arrays([pa.array(v[at].view(np.int64)) for v in (x.word, x.long, x.short)], ["word", "long", "short"])


def _hashed_pairs(batches):
    """Counted pairs by the hash of both words, which is told from them and needn't be kept."""
    for batch in batches:
        before, word = (np.asarray(batch.column(c), dtype=np.int64).view(np.uint64) for c in ("before", "word"))
        counts = [batch.column(c).cast(pa.int32()) for c in ("n0", "n1")]
        yield pa.RecordBatch.from_arrays([pa.array(pair_hash(before, word).view(np.int64)), *counts], ["pair", "n0", "n1"])


def _table(rows: DataFrame, *names: str) -> list[np.ndarray]:
    """The keys in the first column and counts in the others, all of them: a sample of bounded size is behind them."""
    got = rows.select(F.col(names[0]), *(F.col(n).cast("int").alias(n) for n in names[1:])).toArrow()
    return [np.asarray(got[names[0]], dtype=np.int64).view(np.uint64), *(np.asarray(got[n], dtype=np.int32) for n in names[1:])]


def _ranges(rows: DataFrame, *names: str):
    """`_table` in PARTS ranges of unsigned keys, the lowest first, so that the driver holds one at a time."""
    top = F.shiftrightunsigned(names[0], 64 - (PARTS - 1).bit_length())
    for i in range(PARTS):
        yield _table(rows.where(top == i), *names)


def _model(pairs: DataFrame, names: DataFrame) -> Toxicity:
    """All orders of both classes from the counted pairs (before, word, n0, n1), which are written, and names (word, long, short)."""

    def sums(*columns: str) -> list[Column]:
        return [F.sum(c).alias(c) for c in columns]

    def kinds(*columns: str) -> list[Column]:
        return [F.sum((F.col(c) > 0).cast("int")).alias(f"k{c}") for c in columns]

    counted = Counts.joined(pairs.count(), 2, _ranges(pairs.mapInArrow(_hashed_pairs, "pair long, n0 int, n1 int"), "pair", "n0", "n1"))
    both = pairs.withColumn("n", F.col("n0") + F.col("n1"))
    after = Counts.of(*_table(both.groupBy("before").agg(*sums("n0", "n1", "n"), *kinds("n0", "n1", "n")), "before", "n0", "n1", "n", "kn0", "kn1", "kn"))
    seen = pairs.groupBy("word").agg(*kinds("n0", "n1"), F.count("*").alias("n")).join(names, "word")
    seen = level = materialize(seen.withColumnsRenamed({"kn0": "n0", "kn1": "n1"}), "words")  # each order below is made from it
    words = Counts.of(*_table(level, "word", "n0", "n1", "n"))
    found = []
    for name, above in (("long", ["short"]), ("short", [])):  # each name has one name above it
        level = level.groupBy(name, *above).agg(*sums("n0", "n1", "n"), *kinds("n0", "n1", "n"))
        found.append(Counts.of(*_table(level, name, "n0", "n1", "n", "kn0", "kn1", "kn")))
        level = level.select(name, *above, "n0", "n1", "n")
    root = level.agg(*sums("n0", "n1", "n"), *kinds("n0", "n1", "n")).first()
    discard(seen)
    return Toxicity(counted, after, words, *found, np.array([root[c] for c in ("n0", "n1", "n", "kn0", "kn1", "kn")], float), np.zeros(FEATURES))


def logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, l2: float = 1.0) -> np.ndarray:
    b = np.zeros(x.shape[1])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        h = (x * (w * p * (1 - p))[:, None]).T @ x + l2 * np.eye(len(b))
        step = np.linalg.solve(h, x.T @ (w * (y - p)) - l2 * b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return b


def fit_toxicity(docs: DataFrame, labels: DataFrame, mod: int = 3, held: int = 1) -> tuple[Broadcast, np.ndarray]:
    """The model, its counts broadcast, and the weights of the evidence."""
    spark = docs.sparkSession
    prepare_workers(spark)
    sample = materialize(sample_texts(docs, labels, "toxic", mod, held, SAMPLE), "sample")
    classes = {r["label"] for r in sample.select("label").distinct().collect()}
    if len(classes) < 2:
        discard(sample)
        weights = np.array([-30.0] + [0.0] * (FEATURES - 1))
        return spark.sparkContext.broadcast(nothing(weights)), weights
    rows = sample.mapInArrow(_pairs, "before long, word long, label int").groupBy("before", "word")
    rows = materialize(rows.agg(F.sum(1 - F.col("label")).alias("n0"), F.sum("label").alias("n1")), "counts")
    collect_garbage(spark)
    names = sample.mapInArrow(_names, "word long, long long, short long").groupBy("word").agg(*(F.min(c).alias(c) for c in ("long", "short")))
    model = _model(rows, names)
    discard(rows)
    counts = spark.sparkContext.broadcast(model)
    del model

    def training(batches):
        for batch in batches:
            labels_, weights = np.asarray(batch.column("label")), np.asarray(batch.column("weight"))
            for i, j, borders, hashes in hashed_spans(batch.column("text"), LETTERS):
                x = counts.value.features(borders, words_of(borders, hashes), labels_[i:j].astype(int))
                yield pa.RecordBatch.from_arrays([pa.array(labels_[i:j].astype(np.int32)), pa.array(weights[i:j]), pa.array(list(x), pa.list_(pa.float64()))], ["label", "weight", "x"])

    got = sample.mapInArrow(training, "label int, weight double, x array<double>").toPandas()
    discard(sample)
    x = np.array(got["x"].tolist(), float)
    order = np.lexsort(np.column_stack([x, got["label"]]).T)
    return counts, logistic(x[order], got["label"].to_numpy(float)[order], got["weight"].to_numpy(float)[order])


def toxicity_score(counts: Broadcast, weights: np.ndarray):
    @F.arrow_udf("double")
    def score(text: pa.Array) -> pa.Array:
        return pa.array(replace(counts.value, weights=weights).score(text))

    return score


def score_toxicity(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """docs (doc_id, text), labels (doc_id, toxic) -> doc_id, held_out, score, predicted."""
    score = toxicity_score(*fit_toxicity(docs, labels))
    scored = docs.select("doc_id", F.coalesce(remainder(F.col("doc_id"), 3) == 1, F.lit(False)).alias("held_out"), score(F.col("text").cast("string")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_civil(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """The rows of docs that the models don't call toxic, with all their columns, whatever their names."""
    score = toxicity_score(*fit_toxicity(docs, labels))
    return docs.where(score(F.col("text").cast("string")) < threshold)
