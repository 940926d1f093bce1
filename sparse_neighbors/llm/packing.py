"""Best-fit packing of token sequences by exact complements.

Only the number of pieces of each length (at most `capacity` numbers) is looked at to plan. Lengths are taken from
the longest: its gap is filled exactly by a single length, else by a pair, else by a triple, found among the sums of
the lengths that are still available, and used as often as the counts allow. What can't be filled exactly is packed
best-fit: longest first into the smallest gap that takes it. The plan says for each run of equal lengths, by rank,
which run of sequences it goes to and at which offset; its size follows the number of lengths, not of documents.

Ranks within a length come from a count per input shard and length (so equal lengths, even all rows, never meet in one
task) and an offset table; pieces then look up their place.

Results for odd input: a null or empty text is one piece that holds only the end id; a null doc_id stays null; rows
that repeat are packed as often as they occur; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import giving_back, materialize, prepare_workers, release_heap, short_batches
from .tokens import encoded

MOST_OFFSETS = 500_000  # rows of the offset table (shards x lengths) that are broadcast; a larger one is joined by a shuffle
BATCH = 1000  # texts that travel to a worker at once
PIECES = "shard int, nth long, doc_id long, piece int, start long, length long, ids_crc32 long"


def _pieces(path: str, end_id: int, capacity: int):
    def run(batches):
        shard, counts = TaskContext.get().partitionId(), defaultdict(int)
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            rows, ids = [], batch.column("doc_id").cast(pa.int64()).to_pylist()
            for row, tokens in encoded(batch.column("text"), path):
                tokens += end
                n = len(tokens) // 4
                first = n % capacity or min(n, capacity)
                cuts = [0, *range(first, n + 1, capacity)]
                for piece, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    rows.append((shard, counts[b - a], ids[row], piece, a, b - a, zlib.crc32(tokens[4 * a : 4 * b])))
                    counts[b - a] += 1
            if rows:
                kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
                names = [c.split()[0] for c in PIECES.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return run


class Plan:
    """Rows (length, first rank, first sequence, offset); a row's ranks end where the next row of its length begins."""

    def __init__(self, capacity: int, counts: dict[int, int]):
        self.capacity = capacity
        self.left = np.zeros(capacity + 1, np.int64)
        for length, n in counts.items():
            self.left[length] = n
        self.taken = np.zeros(capacity + 1, np.int64)
        self.rows: list[tuple[int, int, int, int]] = []
        self.sequences = 0
        self._fill_exactly()
        self._fit_rest()
        self.rows.sort()

    def _put(self, length: int, n: int, sequence: int, offset: int) -> None:
        self.rows.append((length, int(self.taken[length]), sequence, offset))
        self.taken[length] += n
        self.left[length] -= n

    def _use(self, combination: tuple[int, ...]) -> None:
        lengths, times = np.unique(combination, return_counts=True)
        n = int((self.left[lengths] // times).min())
        offset = 0
        for length in combination:
            self._put(length, n, self.sequences, offset)
            offset += length
        self.sequences += n

    def _available(self, combination: tuple[int, ...]) -> bool:
        lengths, times = np.unique(combination, return_counts=True)
        return bool((self.left[lengths] >= times).all())

    def _pair(self, total: int, most: int) -> tuple[int, int] | None:
        """Two available lengths of at most `most` that sum to total, the larger as large as can be."""
        top = min(total - 1, most)
        low = (total + 1) // 2
        if top < low:
            return None
        larger = np.arange(top, low - 1, -1)
        fits = (self.left[larger] > 0) & (self.left[total - larger] > 0)
        if total % 2 == 0 and self.left[low] < 2:
            fits[-1] = False
        at = int(fits.argmax())
        return (int(larger[at]), int(total - larger[at])) if fits[at] else None

    def _complement(self, longest: int) -> tuple[int, ...] | None:
        """Available lengths, at most `longest` each, that fill the gap beside it exactly: one, two or three."""
        gap = self.capacity - longest
        if gap == 0:
            return (longest,)
        self.left[longest] -= 1
        try:
            if gap <= longest and self.left[gap] > 0:
                return longest, gap
            if pair := self._pair(gap, longest):
                return longest, *pair
            for third in np.flatnonzero(self.left[: min(gap - 1, longest) + 1])[::-1]:
                self.left[third] -= 1
                pair = self._pair(gap - int(third), int(third))
                self.left[third] += 1
                if pair:
                    return longest, int(third), *pair
        finally:
            self.left[longest] += 1
        return None

    def _fill_exactly(self) -> None:
        for longest in range(self.capacity, 0, -1):
            while self.left[longest] and (found := self._complement(longest)):
                self._use(found)

    def _fit_rest(self) -> None:
        """Longest first into the smallest gap that takes it; equal lengths and equal gaps go together."""
        gaps: dict[int, list[tuple[int, int]]] = defaultdict(list)  # gap -> runs (first sequence, number)
        for length in range(self.capacity, 0, -1):
            while self.left[length]:
                gap = next((g for g in range(length, self.capacity) if gaps[g]), None)
                if gap is None:
                    break
                sequence, n = gaps[gap].pop()
                used = min(n, int(self.left[length]))
                self._put(length, used, sequence, self.capacity - gap)
                if used < n:
                    gaps[gap].append((sequence + used, n - used))
                gaps[gap - length].append((sequence, used))
            each = self.capacity // length
            for number in (int(self.left[length]) // each, 1):
                held = min(each, int(self.left[length]))
                if number and held:
                    for i in range(held):
                        self._put(length, number, self.sequences, i * length)
                    gaps[self.capacity - held * length].append((self.sequences, number))
                    self.sequences += number

    def arrays(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        rows = np.array(self.rows, np.int64).reshape(-1, 4)
        return (rows[:, 0] << 44) + rows[:, 1], rows[:, 2] - rows[:, 1], rows[:, 3]


def _places(plan: Plan):
    keys, shift, offset = plan.arrays()

    def run(batches):
        for batch in batches:
            length, rank = (np.asarray(batch.column(c), dtype=np.int64) for c in ("length", "rank"))
            at = np.searchsorted(keys, (length << 44) + rank, "right") - 1
            keep = batch.select(["doc_id", "piece", "start", "length", "ids_crc32"])
            yield pa.RecordBatch.from_arrays([*keep.columns, pa.array(shift[at] + rank), pa.array(offset[at])], [*keep.schema.names, "sequence_id", "offset"])

    return run


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = 2048) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    `tokenizer` is the path of a vocabulary file of the tokenizers library, there on every machine.
    A document longer than the capacity is cut into full pieces behind a first one that may be shorter.
    """
    prepare_workers(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    release_heap(docs.sparkSession)
    with short_batches(docs.sparkSession, BATCH):
        pieces = materialize(texts.mapInArrow(giving_back(_pieces(tokenizer, end_id, capacity)), PIECES), "pieces")
    counts = pieces.groupBy("length", "shard").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    counts = materialize(counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))), "ranks")
    histogram = counts.groupBy("length").agg(F.sum("n").alias("n"), F.count("*").alias("shards")).collect()  # at most `capacity` rows
    plan = Plan(capacity, {r["length"]: r["n"] for r in histogram})
    offsets = counts.select("length", "shard", "base")
    offsets = F.broadcast(offsets) if sum(r["shards"] for r in histogram) <= MOST_OFFSETS else offsets.hint("merge")
    ranked = pieces.join(offsets, ["length", "shard"]).withColumn("rank", F.col("base") + F.col("nth"))
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank")
    return ranked.mapInArrow(_places(plan), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
