"""Scores of all pairs that share a dimension, streamed out of cells: nothing is shuffled by pair, and no cell holds its result.

A task gets a cell's rows of R first and keeps their posting lists; vectors of S follow, and the pairs of a few of them at a time go out.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PAIRS = 1 << 19  # of a slice of S with all of a cell's R, or one vector of S if that's more


class _Lists:
    """The posting lists of a cell's rows of R."""

    def __init__(self, rows: list[pa.RecordBatch], weight):
        ids, names, w = (pa.chunked_array([b.column(c) for b in rows]) for c in ("id", "d", "w"))
        self.weight, self.names = weight, pc.unique(names)
        self.ids, at = np.unique(np.asarray(ids), return_inverse=True)
        d, w = np.asarray(pc.index_in(names, self.names), dtype=np.int64), np.asarray(w, dtype=weight)
        order = np.argsort(d, kind="stable")
        self.borders = np.searchsorted(d[order], np.arange(len(self.names) + 1))
        self.owner, self.w = at[order], w[order]
        order = np.argsort(at, kind="stable")  # the vectors themselves, one slice each
        self.cuts = np.searchsorted(at[order], np.arange(len(self.ids) + 1))
        self.own_d, self.own_w = d[order], w[order]

    def _slices(self, rows: pa.Table, width: int = 1):
        """(ids, id of each row, d, w, is_tail) of a few whole vectors of S, whose rows stand together; dimensions that R lacks are left out."""
        d = pc.index_in(rows["d"], self.names)
        rows = rows.filter(pc.is_valid(d))
        if not len(rows):
            return
        d = np.asarray(pc.drop_null(d), dtype=np.int64)
        ids, w = np.asarray(rows["id"]), np.asarray(rows["w"], dtype=self.weight)
        tail = np.asarray(rows["is_tail"], dtype=bool) if "is_tail" in rows.column_names else None
        first = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
        ends, step = np.r_[first[1:], len(ids)], max(1, PAIRS // max(len(self.ids), width))
        for a in range(0, len(first), step):
            own = slice(first[a], ends[min(a + step, len(first)) - 1])
            sid = ids[first[a : a + step]]
            yield sid, np.searchsorted(sid, ids[own]), d[own], w[own], None if tail is None else tail[own]

    def _met(self, sid, owner, d):
        """(postings, spot of each in the grid of sid and R, spots that are met)."""
        size = self.borders[d + 1] - self.borders[d]
        at = np.repeat(self.borders[d] - np.cumsum(size) + size, size) + np.arange(size.sum())
        spot = np.repeat(owner, size) * len(self.ids) + self.owner[at]
        met = np.zeros(len(sid) * len(self.ids), bool)
        met[spot] = True
        return at, size, spot, np.flatnonzero(met)

    def _batch(self, sid, found, score):
        return pa.RecordBatch.from_arrays([pa.array(self.ids[found % len(self.ids)]), pa.array(sid[found // len(self.ids)]), pa.array(score)], ["r_id", "s_id", "score"])

    def _sums(self, sid, owner, d, w):
        at, size, spot, found = self._met(sid, owner, d)
        score = np.zeros(len(sid) * len(self.ids), self.weight)
        np.add.at(score, spot, np.repeat(w, size) * self.w[at])
        return found, score[found]

    def pairs(self, rows: pa.Table):
        """Scores of the pairs that share a dimension."""
        for sid, owner, d, w, _ in self._slices(rows):
            yield self._batch(sid, *self._sums(sid, owner, d, w))

    def candidates(self, rows: pa.Table):
        """Scores of the pairs that share a dimension with the tail: sums over the tail, and for these pairs alone the product of r with the head."""
        most = max(1, PAIRS // int(np.diff(self.cuts).max()))
        for sid, owner, d, w, tail in self._slices(rows, len(self.names)):
            found, score = self._sums(sid, owner[tail], d[tail], w[tail])
            heads = np.zeros((len(sid), len(self.names)), self.weight)
            heads[owner[~tail], d[~tail]] = w[~tail]
            for a in range(0, len(found), most):
                some = found[a : a + most]
                r = some % len(self.ids)
                size = self.cuts[r + 1] - self.cuts[r]
                begin = np.cumsum(size) - size
                at = np.repeat(self.cuts[r] - begin, size) + np.arange(size.sum())
                more = heads[np.repeat(some // len(self.ids), size), self.own_d[at]] * self.own_w[at]
                yield self._batch(sid, some, score[a : a + most] + np.add.reduceat(more, begin))

    def meetings(self, rows: pa.Table):
        """Every vector of S that shares a dimension with some of R: its id, its features and the ids of these."""
        ids = np.asarray(rows["id"])
        for sid, owner, d, _, _ in self._slices(rows):
            found = self._met(sid, owner, d)[3]
            low, high = np.searchsorted(ids, sid), np.searchsorted(ids, sid, "right")
            own = rows.slice(low[0], high[-1] - low[0])
            own = own.take(pa.array(np.concatenate([np.arange(x, y) for x, y in zip(low, high, strict=True)]) - low[0]))
            parts = pa.StructArray.from_arrays([own[c].combine_chunks() for c in ("d", "w")], ["d", "w"])
            ends = [pa.array(np.r_[0, np.cumsum(x)], pa.int32()) for x in (high - low, np.bincount(found // len(self.ids), minlength=len(sid)))]
            r_ids = pa.array(self.ids[found % len(self.ids)])
            yield pa.RecordBatch.from_arrays([pa.array(sid), pa.ListArray.from_arrays(ends[0], parts), pa.ListArray.from_arrays(ends[1], r_ids)], ["s_id", "b", "r_ids"])


def _stream(whole: bool, how: str = "pairs", per_block: int = 0):
    """What the method `how` of a cell's lists gives for its vectors of S; with the number of an R-block's cells, the block comes first."""
    weight = np.int64 if whole else np.float64

    def given(lists, waiting, cell):
        for out in getattr(lists, how)(pa.Table.from_batches(waiting)):
            yield out.add_column(0, "rb", pa.array(np.full(len(out), cell // per_block, np.int32))) if per_block else out

    def run(batches):
        cell, outer, lists, waiting = None, [], None, []
        for batch in batches:
            key = np.asarray(batch.column("cell")) * 2 + np.asarray(batch.column("inner"))
            for a, b in zip(cuts := np.flatnonzero(np.r_[True, key[1:] != key[:-1]]), np.r_[cuts[1:], len(key)], strict=True):
                part = batch.slice(a, b - a)
                if key[a] // 2 != cell:
                    if lists and waiting:
                        yield from given(lists, waiting, cell)
                    cell, outer, lists, waiting = key[a] // 2, [], None, []
                if key[a] % 2 == 0:
                    outer.append(part)
                    continue
                if lists is None and outer:
                    lists, outer = _Lists(outer, weight), []
                if lists is None:  # no vector of R here
                    continue
                ids = np.asarray(part.column("id"))
                last = int(np.searchsorted(ids, ids[-1]))  # the last vector may go on in the next batch
                if last:
                    yield from given(lists, [*waiting, part.slice(0, last)], cell)
                    waiting = []
                elif waiting and waiting[-1].column("id")[-1].as_py() != ids[-1]:
                    yield from given(lists, waiting, cell)
                    waiting = []
                waiting.append(part.slice(last))
        if lists and waiting:
            yield from given(lists, waiting, cell)

    return run


def _whole(r: DataFrame) -> bool:
    return r.schema["w"].dataType.simpleString() in ("bigint", "int", "smallint", "tinyint")


def _every(n: int):
    return F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint")))


def _of(n: int, id: str = "id"):
    return F.pmod(F.xxhash64(id), F.lit(n))


def _cells(r: DataFrame, s: DataFrame, grid: tuple[int, int]) -> DataFrame:
    """Rows (cell, inner, id, d, w) of both sides in a partition a cell, those of R first, vectors together."""
    n_r, n_s = grid
    w = F.col("w").cast("long" if _whole(r) else "double").alias("w")
    left = r.select(_of(n_r).alias("rc"), _every(n_s).alias("sc"), F.lit(0).cast("long").alias("inner"), F.col("id").cast("long").alias("id"), "d", w)
    right = s.select(_every(n_r).alias("rc"), _of(n_s).alias("sc"), F.lit(1).cast("long").alias("inner"), F.col("id").cast("long").alias("id"), "d", w)
    rows = left.unionByName(right).where("id is not null and d is not null").select((F.col("rc") * n_s + F.col("sc")).alias("cell"), "inner", "id", "d", "w")
    return rows.repartition(n_r * n_s, "cell")


def pair_scores(r: DataFrame, s: DataFrame, grid: tuple[int, int]) -> DataFrame:
    """(r_id, s_id, score) of all pairs of r and s (id, d, w) that share a dimension, through a grid of cells; a null id or dimension meets nothing."""
    rows = _cells(r, s, grid).sortWithinPartitions("cell", "inner", "id")
    return rows.mapInArrow(_stream(_whole(r)), f"r_id long, s_id long, score {'long' if _whole(r) else 'double'}")


def met_pairs(r: DataFrame, s: DataFrame, grid: tuple[int, int]) -> DataFrame:
    """(r_id, s_id, b) of the same pairs, b being the features of s sorted by d; they leave a cell as one row for each s."""
    rows = _cells(r, s, grid).sortWithinPartitions("cell", "inner", "id", "d")
    d, w = rows.schema["d"].dataType.simpleString(), "long" if _whole(r) else "double"
    met = rows.mapInArrow(_stream(_whole(r), "meetings"), f"s_id long, b array<struct<d:{d},w:{w}>>, r_ids array<long>")
    return met.select(F.explode("r_ids").alias("r_id"), "s_id", "b")


def block_candidates(r: DataFrame, split: DataFrame, grid: tuple[int, int]) -> DataFrame:
    """(rb, r_id, s_id, score) of all pairs of r (rb, r_id, d, w) and a split (rb, s_id, d, w, is_tail) of the same R-block that share a tail's dimension."""
    n_r, n_s = grid
    w = F.col("w").cast("long" if _whole(r) else "double").alias("w")
    left = r.select("rb", _of(n_r, "r_id").alias("rc"), _every(n_s).alias("sc"), F.lit(0).cast("long").alias("inner"), F.col("r_id").cast("long").alias("id"), "d", w, F.lit(True).alias("is_tail"))
    right = split.select("rb", _every(n_r).alias("rc"), _of(n_s, "s_id").alias("sc"), F.lit(1).cast("long").alias("inner"), F.col("s_id").cast("long").alias("id"), "d", w, "is_tail")
    rows = left.unionByName(right).where("id is not null and d is not null").select(((F.col("rb") * n_r + F.col("rc")) * n_s + F.col("sc")).alias("cell"), "inner", "id", "d", "w", "is_tail")
    tasks = int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.repartition(max(tasks, n_r * n_s), "cell").sortWithinPartitions("cell", "inner", "id")
    return rows.mapInArrow(_stream(_whole(r), "candidates", n_r * n_s), f"rb int, r_id long, s_id long, score {'long' if _whole(r) else 'double'}")
