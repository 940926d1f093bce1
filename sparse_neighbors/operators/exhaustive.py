"""The exhaustive join, the baseline: every pair is scored by a sorted merge.

It needs every pair by definition, so it is guarded by a limit on their number and exists to be compared with.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.similarity import merge_dot
from ..functions.vectors import pack
from .topk import top_k

MOST_PAIRS = 2_000_000_000
PAIRS_A_TASK = 20_000


def guard(r: DataFrame, s: DataFrame, most: int = MOST_PAIRS) -> int:
    """The number of pairs, refused beyond a limit."""
    n = r.select("id").distinct().count() * s.select("id").distinct().count()
    if n > most:
        raise ValueError(f"{n} pairs; the exhaustive join is limited to {most}")
    return n


def spread(side: DataFrame, pairs: int) -> DataFrame:
    """A side of the pairs in as many partitions that both sides together give tasks of a bounded number of pairs.

    Packed vectors are few bytes for the work they cause, so without a number they would end in one task.
    """
    return side.repartition(max(1, math.ceil(math.sqrt(pairs / PAIRS_A_TASK))))


def exhaustive_block(r_block: DataFrame, s_block: DataFrame, kind: str = "bigint") -> DataFrame:
    """Scores of all pairs of a block of R (rb, r_id, features) and a block of S (s_id, features)."""
    pairs = r_block.crossJoin(s_block.withColumnRenamed("features", "s_features"))
    return pairs.select("rb", "r_id", "s_id", merge_dot(F.col("features"), F.col("s_features"), kind).alias("score")).where("score > 0")


def exhaustive_join(r: DataFrame, s: DataFrame, k: int = 5, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """The whole-set form in one job."""
    pairs = guard(r, s)
    kind = r.schema["w"].dataType.simpleString()
    left = pack(r).select(F.lit(0).alias("rb"), F.col("id").alias("r_id"), "features")
    right = pack(s).select(F.col("id").alias("s_id"), "features")
    scores = exhaustive_block(spread(left, pairs), spread(right, pairs), kind).drop("rb")
    return top_k(scores.where("r_id <> s_id") if exclude_self else scores, k, ties)


def _cell(k: int, ties: str, exclude_self: bool, whole: bool):
    """Scores of one cell of the grid, each r merged with all s of the cell at once; what can't be in the result of the cell stays behind."""

    def run(r: pa.Table, s: pa.Table) -> pa.Table:
        weight = np.int64 if whole else np.float64
        rid, rpos = np.unique(np.asarray(r["r_id"]), return_inverse=True)
        sid, spos = np.unique(np.asarray(s["s_id"]), return_inverse=True)
        out = {"r_id": [np.zeros(0, np.int64)], "s_id": [np.zeros(0, np.int64)], "score": [np.zeros(0, weight)]}
        if len(rid) and len(sid):
            names = pc.unique(pa.chunked_array([*r["r_d"].chunks, *s["s_d"].chunks]))
            rd, sd = (np.asarray(pc.index_in(x, names), dtype=np.int64) for x in (r["r_d"], s["s_d"]))
            by_d = np.argsort(sd, kind="stable")  # the cell's lists: sorted by dimension, one slice each
            lists = np.searchsorted(sd[by_d], np.arange(len(names) + 1))
            owner, sw, rw = spos[by_d], np.asarray(s["s_w"], dtype=weight)[by_d], np.asarray(r["r_w"], dtype=weight)
            by_r = np.argsort(rpos, kind="stable")
            cuts = np.searchsorted(rpos[by_r], np.arange(len(rid) + 1))
            for i in range(len(rid)):
                score = np.zeros(len(sid), weight)
                for at in by_r[cuts[i] : cuts[i + 1]]:
                    a, b = lists[rd[at]], lists[rd[at] + 1]
                    score[owner[a:b]] += rw[at] * sw[a:b]
                if exclude_self:
                    score[sid == rid[i]] = 0
                met = np.flatnonzero(score > 0)
                if len(met) > k:  # the k-th best without sorting the others
                    met = met[score[met] >= np.partition(score[met], len(met) - k)[len(met) - k]]
                best = met[np.lexsort((sid[met], -score[met]))]
                if ties == "id" or len(best) <= k:
                    best = best[:k]
                else:  # whole groups of equal scores, for the ranks over all cells
                    best = best[score[best] >= score[best[k - 1]]]
                out["r_id"].append(np.full(len(best), rid[i]))
                out["s_id"].append(sid[best])
                out["score"].append(score[best])
        return pa.table({c: np.concatenate(v) for c, v in out.items()})

    return run


def exhaustive_grid(r: DataFrame, s: DataFrame, k: int = 5, r_blocks: int = 2, s_blocks: int = 2, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """Every cell of R-blocks and S-blocks is one group, so memory is bounded by the block counts. Scores have the weights' own type."""
    guard(r, s)
    return cell_join(r, s, k, r_blocks, s_blocks, ties, exclude_self)


def cell_join(r: DataFrame, s: DataFrame, k: int, r_blocks: int, s_blocks: int, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """The k best over all cells of R-blocks and S-blocks."""
    return top_k(cell_scores(r, s, k, r_blocks, s_blocks, ties, exclude_self), k, ties)


def cell_scores(r: DataFrame, s: DataFrame, k: int, r_blocks: int, s_blocks: int, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """Posting lists in every cell of R-blocks and S-blocks: what leaves a cell is k rows per r, or what ties with them."""
    kind = r.schema["w"].dataType.simpleString()
    whole = kind in ("bigint", "int", "smallint", "tinyint")
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint")))
    left = r.select(F.col("id").alias("r_id"), F.col("d").alias("r_d"), F.col("w").alias("r_w"), F.pmod(F.xxhash64("id"), F.lit(r_blocks)).alias("rb"), every(s_blocks).alias("sb"))
    right = s.select(F.col("id").alias("s_id"), F.col("d").alias("s_d"), F.col("w").alias("s_w"), every(r_blocks).alias("rb2"), F.pmod(F.xxhash64("id"), F.lit(s_blocks)).alias("sb2"))
    cells = left.groupBy("rb", "sb").cogroup(right.groupBy("rb2", "sb2"))
    return cells.applyInArrow(_cell(k, ties, exclude_self, whole), f"r_id long, s_id long, score {'long' if whole else 'double'}")
