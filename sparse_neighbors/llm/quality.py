"""Quality classifier: histogram gradient-boosted trees over statistics of the whole text.

The statistics are counts and ratios of bytes, words and lines. Trees are grown on binned statistics of a bounded
sample of labelled documents and kept as flat arrays, which a batch of documents walks level by level in numpy.

Results for odd input: a null or empty text gets the score of its (all zero) statistics; without any label the score
is 0.5, and with labels of one class only a constant near it; a null doc_id is scored and never held out; rows that
repeat are scored alike; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labelled import remainder, sample_texts
from .shared import prepare_workers
from .textscan import bytes_and_offsets, joined_sum, mix64, slices, span_hashes, span_sums, word_spans

SAMPLE = {0: 20_000, 1: 30_000}  # labelled documents of each class that the trees may be fitted on
BINS, DEPTH, TREES, RATE, L2 = 64, 4, 80, 0.15, 2.0


def _marks(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[np.frombuffer(chars.encode(), np.uint8)] = True
    return out


UPPER = _marks("ABCDEFGHIJKLMNOPQRSTUVWXYZ")
DIGIT = _marks("0123456789")
STOP = _marks(".,;:?")
SHOUT = _marks("!")
SYMBOL = _marks("#$%&*+=<>@^~_|{}[]\\/")
OTHER = _marks("'\"()-`")
BEYOND = np.arange(256) >= 128
LINE = _marks("\n")
BYTE_SETS = (UPPER, DIGIT, STOP, SHOUT, SYMBOL, OTHER, BEYOND, LINE)


def statistics(column: pa.Array) -> np.ndarray:
    """One row of document statistics per text."""
    raw, offsets = bytes_and_offsets(column)
    n = len(offsets) - 1
    sets, words = np.zeros((n, len(BYTE_SETS))), np.zeros((n, 8))
    varied = np.zeros((n, 4))
    held: list[tuple[np.ndarray, np.ndarray]] = []  # word and line hashes of a long text's earlier slices
    begun = (np.uint64(0), 0)  # sum and size of the line that its last slice cut
    for i, j, a, b in slices(raw, offsets):
        part = raw[a:b]
        cuts = np.clip(offsets[i : j + 1], a, b) - a
        for s, marks in enumerate(BYTE_SETS):
            sets[i:j, s] += np.diff(np.concatenate([[0], np.cumsum(marks[part])])[cuts])
        starts, ends, borders = word_spans(part, cuts)
        size = ends - starts
        upper = np.concatenate([[0], np.cumsum(UPPER[part])])
        big = upper[ends] - upper[starts]
        symbol = np.concatenate([[0], np.cumsum((SYMBOL | SHOUT)[part])])
        odd = symbol[ends] - symbol[starts]
        hashes = span_hashes(part, starts, ends)
        again = np.zeros(len(starts), bool)
        again[1:] = hashes[1:] == hashes[:-1]
        again[borders[:-1][np.diff(borders) > 0]] = False
        if held and len(hashes):  # the word before is in an earlier slice
            before = next((own[-1] for own, _ in reversed(held) if len(own)), None)
            again[0] = hashes[0] == before
        columns = (np.ones(len(size)), size, size > 18, size == 1, (big > 1) & (2 * big >= size), odd > 0, odd == size, again)
        for c, values in enumerate(columns):
            words[i:j, c] += np.diff(np.concatenate([[0.0], np.cumsum(values)])[borders])
        line_ends = np.flatnonzero(LINE[part])
        line_cuts = np.unique(np.concatenate([cuts, line_ends + 1]))
        line_sums, line_sizes = span_sums(part, line_cuts[:-1], line_cuts[1:]), np.diff(line_cuts)
        long = b < offsets[j]  # the text goes on in the next slice
        if long or held:
            line_sums[0], line_sizes[0] = joined_sum(*begun, line_sums[0], line_sizes[0])
            begun = (np.uint64(0), 0)
            if long and not LINE[part[-1]]:
                begun = line_sums[-1], line_sizes[-1]
                line_sums, line_sizes = line_sums[:-1], line_sizes[:-1]
        lines = mix64(line_sums + line_sizes.astype(np.uint64))
        line_borders = np.array([0, len(lines)]) if long or held else np.searchsorted(line_cuts[:-1], cuts)
        for t in range(j - i):
            own, own_lines = hashes[borders[t] : borders[t + 1]], lines[line_borders[t] : line_borders[t + 1]]
            if long or held:
                held.append((own, own_lines))
                if long:
                    continue
                own, own_lines = (np.concatenate(x) for x in zip(*held, strict=True))
                held = []
            if len(own):
                counts = np.unique(own, return_counts=True)[1]
                varied[i + t] = len(counts) / len(own), counts.max() / len(own), len(counts) / np.sqrt(len(own)), 1 - len(np.unique(own_lines)) / max(1, len(own_lines))
    size = np.diff(offsets)
    per_byte = sets / np.maximum(size, 1)[:, None]
    per_word = words[:, 1:] / np.maximum(words[:, :1], 1)
    return np.column_stack([np.log1p(size), np.log1p(words[:, 0]), per_byte, per_word, varied, sets[:, 2] / np.maximum(words[:, 0], 1)])


@dataclass
class Trees:
    base: float
    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray
    leaf: np.ndarray  # trees x leaves

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.base)
        rows = np.arange(len(x))
        inner = self.feature.shape[1]
        for f, t, leaf in zip(self.feature, self.threshold, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            while inner and node[:1].size and node[0] < inner:  # all rows are on the same level
                node = 2 * node + 1 + (x[rows, f[node]] > t[node])
            total += leaf[node - inner]
        return 1 / (1 + np.exp(-total))


def fit_trees(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> Trees:
    """Boosting of depth-bounded trees on the logistic loss, splits from histograms of binned columns."""
    mean = (w @ y + 1) / (w.sum() + 2)
    base = float(np.log(mean / (1 - mean)))
    inner = (1 << DEPTH) - 1
    if len(np.unique(y)) < 2:
        return Trees(base, np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)))
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS)[1:-1])) for f in range(x.shape[1])]
    binned = np.column_stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)])  # bin b: x <= edges[b]
    columns = np.arange(x.shape[1]) * BINS
    total = np.full(len(x), base)
    found = []
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-total))
        grad, hess = w * (p - y), w * p * (1 - p)
        node = np.zeros(len(x), np.int64)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf)
        for level in range(DEPTH):
            first, n = (1 << level) - 1, 1 << level
            cell = ((node - first)[:, None] * (x.shape[1] * BINS) + columns + binned).ravel()
            shape = (n, x.shape[1], BINS)
            g = np.bincount(cell, np.repeat(grad, x.shape[1]), np.prod(shape)).reshape(shape).cumsum(2)
            h = np.bincount(cell, np.repeat(hess, x.shape[1]), np.prod(shape)).reshape(shape).cumsum(2)
            gt, ht = g[:, :, -1:], h[:, :, -1:]
            gain = g**2 / (h + L2) + (gt - g) ** 2 / (ht - h + L2) - gt**2 / (ht + L2)
            gain[(h < 1) | (ht - h < 1)] = 0
            best = gain.reshape(n, -1).argmax(1)
            for k in range(n):
                f, b = divmod(int(best[k]), BINS)
                if gain[k, f, b] > 1e-6 and b < len(edges[f]):
                    feature[first + k], threshold[first + k] = f, edges[f][b]
            node = 2 * node + 1 + (x[np.arange(len(x)), feature[node]] > threshold[node])
        at = node - inner
        leaf = -RATE * np.bincount(at, grad, inner + 1) / (np.bincount(at, hess, inner + 1) + L2)
        total += leaf[at]
        found.append((feature, threshold, leaf))
    return Trees(base, *map(np.array, zip(*found, strict=True)))


def fit_quality(docs: DataFrame, labels: DataFrame, mod: int = 5, held: int = 0) -> Trees:
    prepare_workers(docs.sparkSession)

    def rows(batches):
        for batch in batches:
            x = statistics(batch.column("text")).astype("<f8")
            yield pa.RecordBatch.from_arrays([batch.column("label"), batch.column("weight"), pa.array([r.tobytes() for r in x], pa.binary())], ["label", "weight", "x"])

    sample = sample_texts(docs, labels, "quality", mod, held, SAMPLE)
    got = sample.mapInArrow(rows, "label int, weight double, x binary").toPandas()
    width = statistics(pa.array([""])).shape[1]
    x = np.frombuffer(b"".join(got["x"]), "<f8").reshape(-1, width)
    order = np.lexsort(np.column_stack([x, got["label"]]).T) if len(x) else slice(None)  # the same trees whatever order tasks end in
    return fit_trees(x[order], got["label"].to_numpy(float)[order], got["weight"].to_numpy(float)[order])


def quality_score(model: Trees):
    @F.arrow_udf("double")
    def score(text: pa.Array) -> pa.Array:
        return pa.array(model.score(statistics(text)))

    return score


def score_quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """docs (doc_id, text), labels (doc_id, quality) -> doc_id, held_out, score, predicted."""
    score = quality_score(fit_quality(docs, labels))
    scored = docs.select("doc_id", F.coalesce(remainder(F.col("doc_id"), 5) == 0, F.lit(False)).alias("held_out"), score(F.col("text").cast("string")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The rows of docs that the classifier doesn't reject, with all their columns, whatever their names."""
    score = quality_score(fit_quality(docs, labels))
    return docs.where(score(F.col("text").cast("string")) >= threshold)
