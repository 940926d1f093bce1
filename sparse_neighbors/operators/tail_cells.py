"""Pairs of R with the split of an S-block in a grid of cells, for dimensions so frequent that partial sums would outgrow what can be shuffled.

A cell adds up its tails' lists for one r at a time and completes with the heads of those s that pass the check. What leaves it is k scores per
r, or what ties with them, or counts.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SLACK = 1e-9  # on bounds of fractional weights
COUNTED = ("candidates", "completed", "completion_steps")


def split_rows(split: DataFrame) -> DataFrame:
    """rb, s_id, d, w, is_tail, head_bound of every s that has a tail, a row a feature; the windows are partitioned like the walk before them."""
    own = Window.partitionBy("rb", "s_id")
    bound = F.coalesce(F.max(F.when(~F.col("is_tail"), F.col("bound"))).over(own), F.lit(0))
    rows = split.select("rb", "s_id", "d", "w", "is_tail", bound.alias("head_bound"), F.max("is_tail").over(own).alias("some"))
    return rows.where("some").drop("some")


def _cell(k: int, ties: str, exclude_self: bool, whole: bool, precheck: bool, counted: bool):
    def run(r: pa.Table, s: pa.Table) -> pa.Table:
        weight = np.int64 if whole else np.float64
        rid, rpos = np.unique(np.asarray(r["r_id"]), return_inverse=True)
        sid, spos = np.unique(np.asarray(s["s_id"]), return_inverse=True)
        out, counts = {"r_id": [np.zeros(0, np.int64)], "s_id": [np.zeros(0, np.int64)], "score": [np.zeros(0, weight)]}, np.zeros(3, np.int64)
        if len(rid) and len(sid):
            names = pc.unique(pa.chunked_array([*r["r_d"].chunks, *s["s_d"].chunks]))
            rd, sd = (np.asarray(pc.index_in(x, names), dtype=np.int64) for x in (r["r_d"], s["s_d"]))
            rw, sw, tail = np.asarray(r["r_w"], dtype=weight), np.asarray(s["s_w"], dtype=weight), np.asarray(s["is_tail"], dtype=bool)
            positive = rw.min() > 0 and sw.min() > 0
            kth, bound = np.zeros(len(rid), weight), np.zeros(len(sid), weight)
            kth[rpos], bound[spos] = np.asarray(r["kth"], dtype=weight), np.asarray(s["head_bound"], dtype=weight)
            at = np.flatnonzero(tail)
            by_d = at[np.argsort(sd[at], kind="stable")]  # the cell's lists: sorted by dimension, one slice each
            lists = np.searchsorted(sd[by_d], np.arange(len(names) + 1))
            owner, listed = spos[by_d], sw[by_d]
            at = np.flatnonzero(~tail)
            by_s = at[np.argsort(spos[at], kind="stable")]  # the heads, one slice each
            heads = np.searchsorted(spos[by_s], np.arange(len(sid) + 1))
            size = np.diff(heads)
            by_r = np.argsort(rpos, kind="stable")
            cuts = np.searchsorted(rpos[by_r], np.arange(len(rid) + 1))
            own = np.zeros(len(names), weight)
            for i in range(len(rid)):
                mine = by_r[cuts[i] : cuts[i + 1]]
                score, touched = np.zeros(len(sid), weight), None if positive else np.zeros(len(sid), bool)
                for at in mine:
                    a, b = lists[rd[at]], lists[rd[at] + 1]
                    score[owner[a:b]] += rw[at] * listed[a:b]
                    if not positive:
                        touched[owner[a:b]] = True
                met = np.flatnonzero(score if positive else touched)
                can = (score[met] + bound[met]) * (1 + SLACK) >= kth[i] if precheck else np.ones(len(met), bool)
                if counted:
                    merged = size[met][can & (size[met] > 0)]
                    counts += [len(met), len(merged), len(merged) * len(mine) + merged.sum()]
                    continue
                met = met[can]
                n = size[met]
                more = by_s[np.repeat(heads[met] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                own[rd[mine]] = rw[mine]
                np.add.at(score, spos[more], own[sd[more]] * sw[more])
                own[rd[mine]] = 0
                met = met[(score[met] >= kth[i]) & (score[met] > 0)]
                if exclude_self:
                    met = met[sid[met] != rid[i]]
                if len(met) > k:  # the k-th best without sorting the others
                    met = met[score[met] >= np.partition(score[met], len(met) - k)[len(met) - k]]
                best = met[np.lexsort((sid[met], -score[met]))]
                if ties == "id":
                    best = best[:k]
                out["r_id"].append(np.full(len(best), rid[i]))
                out["s_id"].append(sid[best])
                out["score"].append(score[best])
        if counted:
            block = pa.chunked_array([*r["rb"].chunks, *s["rb2"].chunks])[:1].cast(pa.int32())
            return pa.table({"rb": block, **{c: [int(x)] for c, x in zip(COUNTED, counts, strict=True)}})
        block = r["rb"][0].as_py() if len(r) else 0
        found = {c: np.concatenate(v) for c, v in out.items()}
        return pa.table({"rb": np.full(len(found["r_id"]), block, np.int32), **found})

    return run


def _in_cells(r: DataFrame, rows: DataFrame, kth: DataFrame | None, grid: tuple[int, int], schema: str, *how) -> DataFrame:
    """r (rb, r_id, d, w) cogrouped with `split_rows` by R-block and cell."""
    n_r, n_s = grid
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint")))
    known = r.withColumn("kth_score", F.lit(0)) if kth is None else r.join(kth, ["rb", "r_id"], "left")
    left = known.select(F.col("rb").cast("int").alias("rb"), "r_id", F.col("d").alias("r_d"), F.col("w").alias("r_w"), F.coalesce("kth_score", F.lit(0)).alias("kth"), F.pmod(F.xxhash64("r_id"), F.lit(n_r)).alias("rc"), every(n_s).alias("sc"))
    right = rows.select(F.col("rb").cast("int").alias("rb2"), "s_id", F.col("d").alias("s_d"), F.col("w").alias("s_w"), "is_tail", "head_bound", every(n_r).alias("rc2"), F.pmod(F.xxhash64("s_id"), F.lit(n_s)).alias("sc2"))
    whole = r.schema["w"].dataType.simpleString() in ("bigint", "int", "smallint", "tinyint")
    run = _cell(*how[:3], whole, *how[3:])
    return left.groupBy("rb", "rc", "sc").cogroup(right.groupBy("rb2", "rc2", "sc2")).applyInArrow(run, schema.format("long" if whole else "double"))


def tail_scores(r: DataFrame, rows: DataFrame, kth: DataFrame, grid: tuple[int, int], k: int, ties: str = "id", exclude_self: bool = False, precheck: bool = True) -> DataFrame:
    """rb, r_id, s_id, score of pairs that share a tail's dimension and reach their r's k-th score: all that can be among the k best, no pair twice."""
    return _in_cells(r, rows, kth, grid, "rb int, r_id long, s_id long, score {}", k, ties, exclude_self, precheck, False)


def tail_counts(r: DataFrame, rows: DataFrame, kth: DataFrame | None, grid: tuple[int, int]) -> DataFrame:
    """rb, candidates, completed, completion_steps of the R-blocks that have candidates; without kth every candidate that has a head is completed."""
    cells = _in_cells(r, rows, kth, grid, "rb int, candidates long, completed long, completion_steps long", 0, "id", False, kth is not None, True)
    return cells.groupBy("rb").agg(*(F.sum(c).alias(c) for c in COUNTED)).where("candidates > 0")
