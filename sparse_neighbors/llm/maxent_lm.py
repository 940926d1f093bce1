"""Language-model scoring by a hashed maximum-entropy model.

A text is its words and one end token. The model predicts the class of the next token by a softmax over hashed
features (the word before, the two words before, the word two back, endings further back), and the token within its
class by its frequency there. Classes: the end token; and for each of CLUSTERS groups of word endings, one of frequent
and one of other words. In a class of other words, absolute discounting keeps mass for words never seen in training.
The groups come from which endings follow which, counted over all training text.

Training is distributed: each shard goes through all its tokens in minibatches with adaptive gradient steps, and the shards'
weights are averaged by their numbers of tokens, block by block. Scoring runs in sparse numpy batches: the features of a
token are rows of the weight table. What is broadcast is bounded: the weights by the feature buckets, the
frequent words by FREQUENT. All other words meet their counts in a join, summed per text before.

Results for odd input: a null or empty text is its end token; a null doc_id is learned from and not held out; rows that
repeat are learned from and scored each; without training text every count is 0; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .labelled import remainder
from .shared import discard, materialize, prepare_workers
from .textscan import hashed_spans, mix64
from .vector_dedup import kmeans, nearest

FREQUENT = 1 << 16
CLUSTERS = 24
CLASSES = 2 * CLUSTERS + 1
END_CLASS = 2 * CLUSTERS
ENDINGS = 256
DISCOUNT = 0.75
TEMPLATES = (4096, 8192, 2048, ENDINGS + 1, ENDINGS + 1)  # buckets of each kind of feature
OFFSETS = np.concatenate([[0], np.cumsum(TEMPLATES)[:-1]])
ROWS = sum(TEMPLATES)
BLOCK_ROWS = 512
STEP = 16_384  # tokens of a minibatch
RATE = 0.25
SHARD = 1_000_000  # tokens that a training shard should have at least
END = np.uint64(0xE0D)
START = np.uint64(0x57A27)


def token_keys(word: np.ndarray, ending: np.ndarray) -> np.ndarray:
    """The ending's bucket on top of 56 bits of the word's hash."""
    return ((ending & np.uint64(ENDINGS - 1)) << np.uint64(56)) | (word >> np.uint64(8))


def token_streams(column: pa.Array):
    """(first text, past last, borders, keys) with the end token behind each text."""
    for i, j, borders, (word, ending) in hashed_spans(column, (-2,)):
        keys = np.insert(token_keys(word, ending), borders[1:], END)
        yield i, j, borders + np.arange(len(borders)), keys


def endings(keys: np.ndarray) -> np.ndarray:
    """Bucket of each token's ending; the end and start marks have one of their own."""
    out = (keys >> np.uint64(56)).astype(np.int64)
    out[(keys == END) | (keys == START)] = ENDINGS
    return out


def _back(keys: np.ndarray, place: np.ndarray, n: int) -> np.ndarray:
    """Tokens n places back in the same text."""
    out = np.full(len(keys), START)
    out[n:] = keys[:-n]
    out[place < n] = START
    return out


def feature_rows(borders: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Rows of the weight table for each token's context."""
    place = np.arange(len(keys)) - np.repeat(borders[:-1], np.diff(borders))
    one, two = _back(keys, place, 1), _back(keys, place, 2)
    mixed = mix64(one + np.uint64(11))
    hashed = (mixed, mix64(mixed ^ (two * np.uint64(0x9FB21C651E98DF25))), mix64(two + np.uint64(13)))
    out = np.empty((len(keys), len(TEMPLATES)), np.int64)
    for t, h in enumerate(hashed):
        out[:, t] = (h & np.uint64(TEMPLATES[t] - 1)).astype(np.int64)
    out[:, 3] = endings(_back(keys, place, 3))
    out[:, 4] = endings(_back(keys, place, 4))
    return out + OFFSETS


@dataclass
class Vocabulary:
    keys: np.ndarray  # of frequent words, sorted
    counts: np.ndarray
    cluster: np.ndarray  # of each ending
    total: np.ndarray  # tokens of each class in training
    kinds: np.ndarray  # different words of each class of other words, by cluster
    tokens: int
    types: int

    def look_up(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(class, count or 0 where the word isn't among the frequent)."""
        at = np.searchsorted(self.keys, keys)
        at[at == len(self.keys)] = 0
        frequent = self.keys[at] == keys if len(self.keys) else np.zeros(len(keys), bool)
        kind = 2 * self.cluster[(keys >> np.uint64(56)).astype(np.int64)] + ~frequent
        kind[keys == END] = END_CLASS
        return kind, np.where(frequent, self.counts[at], 0) if len(self.keys) else np.zeros(len(keys), np.int64)

    def base(self, count: np.ndarray) -> np.ndarray:
        return np.log10((count + 0.1) / (self.tokens + 0.1 * (self.types + 1)))

    def prior(self) -> np.ndarray:
        return np.log((self.total + 0.5) / (self.total + 0.5).sum()).astype(np.float32)


def probabilities(weights: np.ndarray, prior: np.ndarray, rows: np.ndarray) -> np.ndarray:
    logits = weights[rows[:, 0]] + prior
    for t in range(1, rows.shape[1]):
        logits += weights[rows[:, t]]
    logits -= logits.max(1, keepdims=True)
    np.exp(logits, out=logits)
    logits /= logits.sum(1, keepdims=True)
    return logits


def _count_tokens(batches):
    """Counts of words (kind 0) and of pairs of endings (kind 1), added up over runs of tokens."""
    held, size = [], 0
    pairs = np.zeros((ENDINGS + 1) ** 2, np.int64)

    def words():
        keys, n = np.unique(np.concatenate(held), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(np.zeros(len(keys), np.int32)), pa.array(keys.view(np.int64)), pa.array(n)], ["kind", "key", "n"])

    for batch in batches:
        for _, _, borders, keys in token_streams(batch.column("text")):
            held.append(keys)
            size += len(keys)
            end = endings(keys)
            pairs += np.bincount(end[:-1] * (ENDINGS + 1) + end[1:], minlength=len(pairs))
            if size > 3_000_000:
                yield words()
                held, size = [], 0
    if held:
        yield words()
    at = np.flatnonzero(pairs)
    yield pa.RecordBatch.from_arrays([pa.array(np.ones(len(at), np.int32)), pa.array(at), pa.array(pairs[at])], ["kind", "key", "n"])


def ending_clusters(pairs: np.ndarray) -> np.ndarray:
    """Groups of endings that follow like endings: k-means on the leading factors of their association."""
    pairs = pairs[:ENDINGS, :ENDINGS].astype(float)
    seen = pairs + pairs.T + 0.01
    expected = seen.sum(1, keepdims=True) * seen.sum(0) / seen.sum()
    u, s, _ = np.linalg.svd(np.log((seen + 1) / (expected + 1)))
    x = u[:, :8] * s[:8]
    order = np.argsort(-seen.sum(1), kind="stable")  # seeds are fitted on the commonest endings
    centres = kmeans(x[order[: ENDINGS // 2]], CLUSTERS, rounds=20)
    return nearest(x, centres, 1)[:, 0]


def _train(vocabulary: Vocabulary):
    prior = vocabulary.prior()

    def run(batches):
        weights, past = np.zeros((ROWS, CLASSES), np.float32), np.full((ROWS, CLASSES), 1e-6, np.float32)
        held_rows, held_kinds, size, seen = [], [], 0, 0
        lane = np.arange(CLASSES)

        def update(rows, kinds):
            p = probabilities(weights, prior, rows)
            p[np.arange(len(kinds)), kinds] -= 1
            flat = p.astype(np.float64).ravel()
            for t, n in enumerate(TEMPLATES):
                cells = ((rows[:, t] - OFFSETS[t])[:, None] * CLASSES + lane).ravel()
                grad = (np.bincount(cells, flat, n * CLASSES) / len(kinds)).reshape(n, CLASSES).astype(np.float32)
                a, b = OFFSETS[t], OFFSETS[t] + n
                past[a:b] += grad * grad
                weights[a:b] -= RATE * grad / np.sqrt(past[a:b])

        for batch in batches:
            for _, _, borders, keys in token_streams(batch.column("text")):
                held_rows.append(feature_rows(borders, keys))
                held_kinds.append(vocabulary.look_up(keys)[0])
                size += len(keys)
                if size >= STEP:
                    rows, kinds = np.concatenate(held_rows), np.concatenate(held_kinds)
                    for a in range(0, size - STEP + 1, STEP):
                        update(rows[a : a + STEP], kinds[a : a + STEP])
                    rest = size - size % STEP
                    held_rows, held_kinds, seen, size = [rows[rest:]], [kinds[rest:]], seen + rest, size % STEP
        if size:
            update(np.concatenate(held_rows), np.concatenate(held_kinds))
            seen += size
        if seen:
            blocks = range(-(-ROWS // BLOCK_ROWS))
            data = [(weights[b * BLOCK_ROWS : (b + 1) * BLOCK_ROWS]).astype("<f4").tobytes() for b in blocks]
            yield pa.RecordBatch.from_arrays([pa.array(list(blocks), pa.int32()), pa.array([float(seen)] * len(data)), pa.array(data, pa.binary())], ["block", "tokens", "weights"])

    return run


def _average(batches):
    """Weighted means per block, adding as rows arrive: memory follows the blocks, not the shards."""
    sums: dict[int, list] = {}
    for batch in batches:
        for block, tokens, data in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            own = sums.setdefault(block, [0.0, 0.0])
            own[0] += tokens
            own[1] = own[1] + tokens * np.frombuffer(data, "<f4").astype(float)
    if sums:
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([(s / n).astype("<f4").tobytes() for n, s in sums.values()], pa.binary())], ["block", "weights"])


SCORES = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, model double, others array<long>, times array<int>"


def _score(vocabulary: Vocabulary, weights: np.ndarray):
    prior = vocabulary.prior()
    total = np.log10(np.maximum(vocabulary.total, 1))

    def run(batches):
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            ids, held = batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist()
            for i, j, borders, keys in token_streams(batch.column("text")):
                kind, count = vocabulary.look_up(keys)
                rows = feature_rows(borders, keys)
                own = np.empty(len(keys))
                for a in range(0, len(keys), STEP):
                    p = probabilities(weights, prior, rows[a : a + STEP])
                    own[a : a + STEP] = np.log10(np.maximum(p[np.arange(len(p)), kind[a : a + STEP]], 1e-30))
                own[kind != END_CLASS] -= total[kind[kind != END_CLASS]]
                frequent = count > 0
                inside = frequent & (kind != END_CLASS)
                own[inside] += np.log10(count[inside])
                base = np.where(frequent, vocabulary.base(count), 0)
                sums = [np.add.reduceat(x, borders[:-1]) for x in (frequent.astype(np.int64), base, own)]
                owner = np.repeat(np.arange(j - i), np.diff(borders))
                rest = np.flatnonzero(~frequent)
                order = rest[np.lexsort((keys[rest], owner[rest]))]
                new = np.ones(len(order), bool)
                new[1:] = (keys[order][1:] != keys[order][:-1]) | (owner[order][1:] != owner[order][:-1])
                first = np.flatnonzero(new)
                times = np.diff(np.append(first, len(order))).astype(np.int32)
                cuts = np.searchsorted(owner[order[first]], np.arange(j - i + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(row + np.arange(j - i)), pa.array(ids[i:j], pa.int64()), pa.array(held[i:j], pa.bool_()), pa.array(np.diff(borders)), pa.array(sums[0]), pa.array(sums[1]), pa.array(sums[2]),
                        pa.ListArray.from_arrays(pa.array(cuts), pa.array(keys[order[first]].view(np.int64))), pa.ListArray.from_arrays(pa.array(cuts), pa.array(times)),
                    ],
                    [c.split()[0] for c in SCORES.split(", ")],
                )
                row += j - i

    return run


def _vocabulary(counts: DataFrame) -> tuple[Vocabulary, DataFrame]:
    """The bounded part of the vocabulary, and the words beyond it with their counts."""
    words = counts.where("kind = 0")
    size = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("tokens"), F.count("*").alias("types")).first()
    level = F.floor(F.log2("n") * 16).cast("int")
    by_level = sorted(((r["level"], r["types"]) for r in words.groupBy(level.alias("level")).agg(F.count("*").alias("types")).collect()), reverse=True)
    held, least = 0, None
    for at, types in by_level:  # at most 64 * 16 levels
        if held + types > FREQUENT:
            break
        held, least = held + types, at
    is_end = F.col("key") == F.lit(int(END))
    frequent = is_end if least is None else is_end | (level >= least)
    got = words.where(frequent).select("key", "n").toArrow()
    keys, n = np.asarray(got["key"], dtype=np.int64).view(np.uint64), np.asarray(got["n"], dtype=np.int64)
    order = np.argsort(keys)
    keys, n = keys[order], n[order]
    pairs = np.zeros((ENDINGS + 1) ** 2, np.int64)
    for r in counts.where("kind = 1").collect():  # at most that many
        pairs[r["key"]] = r["n"]
    cluster = ending_clusters(pairs.reshape(ENDINGS + 1, -1))
    others = words.where(~frequent).select("key", "n")
    total, kinds = np.zeros(CLASSES), np.zeros(CLUSTERS)
    own = 2 * cluster[(keys >> np.uint64(56)).astype(np.int64)]
    own[keys == END] = END_CLASS
    np.add.at(total, own, n)
    for r in others.groupBy(F.shiftrightunsigned("key", 56).cast("int").alias("ending")).agg(F.sum("n").alias("n"), F.count("*").alias("types")).collect():
        total[2 * cluster[r["ending"]] + 1] += r["n"]
        kinds[cluster[r["ending"]]] += r["types"]
    return Vocabulary(keys, n, cluster, total, kinds, size["tokens"], size["types"]), others


def score_texts(docs: DataFrame, mod: int = 10, held: int = 0) -> DataFrame:
    """docs (doc_id, text) -> doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    prepare_workers(docs.sparkSession)
    out_of = F.coalesce(remainder(F.col("doc_id"), mod) == held, F.lit(False))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), out_of.alias("held_out"))
    training = texts.where("not held_out").select("text")
    counts = materialize(training.mapInArrow(_count_tokens, "kind int, key long, n long").groupBy("kind", "key").agg(F.sum("n").alias("n")), "counts")
    vocabulary, others = _vocabulary(counts)
    shards = training.coalesce(max(1, min(100_000, vocabulary.tokens // SHARD)))
    trained = shards.mapInArrow(_train(vocabulary), "block int, tokens double, weights binary")
    blocks = -(-ROWS // BLOCK_ROWS)
    averaged = trained.repartition(blocks, "block").mapInArrow(_average, "block int, weights binary").collect()  # the model: ROWS x CLASSES
    weights = np.zeros((blocks * BLOCK_ROWS, CLASSES), np.float32)
    for r in averaged:
        part = np.frombuffer(r["weights"], "<f4").reshape(-1, CLASSES)
        weights[r["block"] * BLOCK_ROWS : r["block"] * BLOCK_ROWS + len(part)] = part
    scored = materialize(texts.mapInArrow(_score(vocabulary, weights[:ROWS]), SCORES), "scores")
    pairs = scored.select("row", F.explode(F.arrays_zip("others", "times")).alias("w")).select("row", F.col("w.others").alias("key"), F.col("w.times").alias("times"))
    met = pairs.join(others, "key", "left")
    # a word never seen: the mass that discounting left in its class
    left = F.array(*(F.lit(float(np.log10(max(1.0, DISCOUNT * k)))) for k in vocabulary.kinds))
    cluster = F.array(*(F.lit(int(c)) for c in vocabulary.cluster))
    unseen = F.element_at(left, F.element_at(cluster, F.shiftrightunsigned("key", 56).cast("int") + 1) + 1)
    model = F.when(F.col("n").isNotNull(), F.log10(F.col("n") - DISCOUNT)).otherwise(unseen)
    per_type = F.lit(vocabulary.tokens + 0.1 * (vocabulary.types + 1))
    base = F.log10((F.coalesce("n", F.lit(0)) + 0.1) / per_type)
    more = met.groupBy("row").agg(F.sum(F.when(F.col("n").isNotNull(), F.col("times")).otherwise(0)).alias("known"), F.sum(base * F.col("times")).alias("more_base"), F.sum(model * F.col("times")).alias("more_model"))
    joined = scored.drop("others", "times").join(more, "row", "left")
    return joined.select(
        "doc_id", "held_out", "n_tokens",
        (F.col("n_known") + F.coalesce("known", F.lit(0))).alias("n_known"),
        F.lit(vocabulary.tokens).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("more_base", F.lit(0.0))).alias("base_score"),
        (F.col("model") + F.coalesce("more_model", F.lit(0.0))).alias("score"),
    )
