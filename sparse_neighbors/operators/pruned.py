"""The floor-pruned join: posting lists hold only what is needed to beat the worst current k-th score of an R-block.

For an R-block, dimensions are ordered by how many of its vectors have them. Walking a vector s of the next S-block in this
order, the running bound adds the block's peak weight times the own weight. Features up to where the bound passes
the block's floor (its least k-th score) form the head and are not indexed; the rest form the tail. A pair that can
still enter a result shares a dimension with the tail; its score is completed with the head.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import merge_dot
from ..sources.scratch import materialize
from .pair_cells import block_candidates
from .tail_cells import SLACK, split_rows, tail_counts, tail_scores


@dataclass(frozen=True)
class PruneOptions:
    """rule: "tie_safe" keeps what can tie with the floor, for any block order; "strict" needs ascending id blocks.

    dim_order: frequent_first, rare_first or natural. drop_dead leaves out dimensions that the R-block lacks. precheck
    skips completing a pair whose partial score and head bound can't reach its r's k-th score.
    """

    rule: str = "tie_safe"
    dim_order: str = "frequent_first"
    drop_dead: bool = True
    precheck: bool = True


def block_dimstats(r: DataFrame, dim_order: str = "frequent_first") -> DataFrame:
    """r (rb, r_id, d, w) -> rb, d, freq, peak_weight, dim_rank."""
    stats = r.groupBy("rb", "d").agg(F.count("*").alias("freq"), F.max("w").alias("peak_weight"))
    order = {"frequent_first": [F.col("freq").desc(), F.col("d")], "rare_first": [F.col("freq"), F.col("d")], "natural": [F.col("d")]}[dim_order]
    return stats.withColumn("dim_rank", F.row_number().over(Window.partitionBy("rb").orderBy(*order)))


def block_floors(kth: DataFrame, live: DataFrame | None = None) -> DataFrame:
    """rb -> block_floor: the least k-th score among the vectors that can meet the coming S-block; a vector without one has 0."""
    if live is not None:
        kth = live.join(kth, ["rb", "r_id"], "left").withColumn("kth_score", F.coalesce("kth_score", F.lit(0)))
    return kth.groupBy("rb").agg(F.min("kth_score").alias("block_floor"))


def live_vectors(r: DataFrame, s_block: DataFrame) -> DataFrame:
    """(rb, r_id) of the vectors that share a dimension with the S-block; all others score 0 with it."""
    return r.join(s_block.select("d").distinct(), "d", "left_semi").select("rb", "r_id").distinct()


def split_features(s_block: DataFrame, dimstats: DataFrame, floors: DataFrame, options: PruneOptions = PruneOptions()) -> DataFrame:
    """s_block (s_id, d, w) -> rb, s_id, d, w, bound, is_tail for every R-block.

    The walk is per R-block and s, so an S-block that is partitioned by s_id isn't shuffled if dimstats is broadcast.
    """
    how = "inner" if options.drop_dead else "left"
    if options.drop_dead:
        rows = s_block.join(dimstats, "d", how)
    else:  # dimensions absent from an R-block come last in its order and add nothing to the bound
        blocks = dimstats.select("rb").distinct()
        rows = s_block.crossJoin(blocks).join(dimstats, ["rb", "d"], "left")
        rows = rows.withColumn("peak_weight", F.coalesce("peak_weight", F.lit(0))).withColumn("dim_rank", F.coalesce("dim_rank", F.lit(2**31 - 1)))
    walk = Window.partitionBy("rb", "s_id").orderBy("dim_rank", "d").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("bound", F.sum(F.col("peak_weight") * F.col("w")).over(walk)).join(floors, "rb")
    fractional = rows.schema["w"].dataType.simpleString() in ("double", "float")
    reach = F.col("bound") * (1 + SLACK) if fractional else F.col("bound")
    passed = (reach >= F.col("block_floor")) & (F.col("bound") > 0) if options.rule == "tie_safe" else reach > F.col("block_floor")
    return rows.select("rb", "s_id", "d", "w", "bound", passed.alias("is_tail"))


def pack_split(split: DataFrame) -> DataFrame:
    """One row per (rb, s_id): tail and head as arrays (head sorted by d), and the bound that the head reaches.

    The grouping is the one of the walk before it, so nothing is shuffled again.
    """
    one, tail = F.struct("d", "w"), F.col("is_tail")
    head = F.array_sort(F.collect_list(F.when(~tail, one)))
    return split.groupBy("rb", "s_id").agg(F.collect_list(F.when(tail, one)).alias("tail"), head.alias("head"), F.coalesce(F.max(F.when(~tail, F.col("bound"))), F.lit(0)).alias("head_bound")).where(F.size("tail") > 0)


def partial_scores(r: DataFrame, packed: DataFrame) -> DataFrame:
    """Sums over the tails: rb, r_id, s_id, score, head_bound."""
    tails = packed.select("rb", "s_id", "head_bound", F.inline("tail")).withColumnRenamed("w", "sw")
    joined = r.withColumnRenamed("w", "rw").join(tails, ["rb", "d"])
    return joined.groupBy("rb", "r_id", "s_id").agg(F.sum(F.col("rw") * F.col("sw")).alias("score"), F.max("head_bound").alias("head_bound"))


def complete(partial: DataFrame, r_packed: DataFrame, packed: DataFrame, kind: str = "bigint", in_place: bool = False) -> DataFrame:
    """Adds to partial (rb, r_id, s_id, score) the product of each r (rb, r_id, features) with the head of its s; pairs without a head pass.

    in_place: both sides are partitioned by s_id already. Then rb is compared behind the join on s_id, since as a second key it
    would make Spark shuffle both again; an s has at most a head per R-block.
    """
    heads = packed.where(F.size("head") > 0).select("rb", "s_id", "head")
    if in_place:
        heads = heads.withColumnsRenamed({"rb": "head_rb", "s_id": "head_s"})
        found = partial.join(heads, (F.col("s_id") == F.col("head_s")) & (F.col("rb") - F.col("head_rb") == 0), "left")
    else:
        found = partial.join(heads, ["rb", "s_id"], "left")
    met = found.join(r_packed, ["rb", "r_id"], "left")
    more = F.when(F.col("head").isNotNull(), merge_dot(F.col("features"), F.col("head"), kind)).otherwise(F.lit(0).cast(kind))
    return met.select("rb", "r_id", "s_id", (F.col("score") + more).alias("score"))


def pruned_block(
    r: DataFrame, s_block: DataFrame, kth: DataFrame, dimstats: DataFrame, options: PruneOptions = PruneOptions(), r_packed: DataFrame | None = None, live: DataFrame | None = None,
    resident: bool = False, write: bool = True, grid: tuple[int, int] | None = None, k: int = 5, ties: str = "id", exclude_self: bool = False,
    every: bool = False,
) -> DataFrame:
    """Scores of an S-block with all R-blocks, for pairs that can still enter a result.

    With the precheck, a pair is completed only if its tail and the bound of its head together reach its r's k-th score.
    resident: r is known to be small enough to go to every task, with its statistics, thresholds and packed form. The S-block is
    then partitioned by s_id once and split, met and completed in place. write: the split is written, and read for the tails
    and for the heads; without it both are made from the same partitions of the S-block. grid: lists are added up in that many cells of R
    and S, and of each r only the k best of a cell, or what ties with them, are given; the split is written as rows then. every: with a grid, all candidates are given, streamed
    out of their cells; they aren't checked.
    """
    kind = r.schema["w"].dataType.simpleString()
    if r_packed is None and not grid:
        r_packed = r.groupBy("rb", "r_id").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("features"))
    floors = block_floors(kth, live_vectors(r, s_block) if live is None else live)
    if grid:
        rows = split_rows(split_features(s_block, dimstats, floors, options))
        rows = materialize(rows, "split") if write else rows
        done = block_candidates(r, rows, grid) if every else tail_scores(r, rows, kth, grid, k, ties, exclude_self, options.precheck)
        done._written, done._floors = rows if write else None, floors
        return done
    if resident:
        s_block = s_block.repartition("s_id")
        r, kth, dimstats, r_packed, floors = (F.broadcast(x) for x in (r, kth, dimstats, r_packed, floors))
    packed = pack_split(split_features(s_block, dimstats, floors, options))
    if write:
        packed = materialize(packed, "split")
    partial = partial_scores(r, packed)
    if options.precheck:
        partial = partial.join(kth, ["rb", "r_id"], "left").where((F.col("score") + F.col("head_bound")) * (1 + SLACK) >= F.coalesce("kth_score", F.lit(0)))
    done = complete(partial.select("rb", "r_id", "s_id", "score"), r_packed, packed, kind, in_place=resident and not write)
    done._written, done._floors = packed if write else None, floors
    return done


def first_block_work(r: DataFrame, s_block: DataFrame, grid: tuple[int, int] | None = None) -> DataFrame:
    """The columns of `pruned_work` for an S-block without floors: everything is indexed and nothing is left to complete."""
    fr = r.groupBy("rb", "d").agg(F.count("*").alias("fr"))
    fs = s_block.groupBy("d").agg(F.count("*").alias("fs"))
    visits = fr.join(fs, "d").groupBy("rb").agg(F.sum(F.col("fr") * F.col("fs")).alias("scanned"))
    if grid:
        rows = s_block.crossJoin(r.select("rb").distinct()).select("rb", "s_id", "d", "w", F.lit(True).alias("is_tail"), F.lit(0).alias("head_bound"))
        pairs = tail_counts(r, rows, None, grid).select("rb", "candidates")
    else:
        pairs = r.select("rb", "r_id", "d").join(s_block.select("s_id", "d"), "d").select("rb", "r_id", "s_id").distinct().groupBy("rb").agg(F.count("*").alias("candidates"))
    cells = r.select("rb").distinct().crossJoin(s_block.agg(F.count("*").alias("indexed")))
    zero = F.lit(0).cast("bigint")
    found = cells.join(visits, "rb", "left").join(pairs, "rb", "left").fillna(0, ["scanned", "candidates"])
    return found.select("rb", F.lit(0).cast(r.schema["w"].dataType).alias("block_floor"), "indexed", "scanned", "candidates", zero.alias("completed"), zero.alias("completion_steps"))


def pruned_work(r: DataFrame, packed: DataFrame, kth: DataFrame, floors: DataFrame, options: PruneOptions = PruneOptions(), grid: tuple[int, int] | None = None) -> DataFrame:
    """What `pruned_block` did with a split that it wrote, per R-block that meets the S-block.

    rb, block_floor, indexed (features of tails), scanned (postings visited), candidates (pairs that share an indexed feature),
    completed (those merged with a head) and completion_steps (features of both sides of these merges).
    """
    fr = r.groupBy("rb", "d").agg(F.count("*").alias("fr"))
    tails = packed.where("is_tail").select("rb", "s_id", "d") if grid else packed.select("rb", "s_id", F.explode("tail.d").alias("d"))
    visits = tails.join(fr, ["rb", "d"], "left").groupBy("rb").agg(F.count("*").alias("indexed"), F.coalesce(F.sum("fr"), F.lit(0)).alias("scanned"))
    if grid:
        done = tail_counts(r, packed, kth if options.precheck else None, grid)
    else:
        sizes = r.groupBy("rb", "r_id").agg(F.count("*").alias("nr"))
        heads = packed.select("rb", "s_id", F.size("head").alias("nh"))
        pairs = partial_scores(r, packed).join(kth, ["rb", "r_id"], "left").join(sizes, ["rb", "r_id"]).join(heads, ["rb", "s_id"])
        merged = F.col("nh") > 0
        if options.precheck:
            merged = merged & ((F.col("score") + F.col("head_bound")) * (1 + SLACK) >= F.coalesce("kth_score", F.lit(0)))
        done = pairs.groupBy("rb").agg(F.count("*").alias("candidates"), F.count(F.when(merged, 1)).alias("completed"), F.coalesce(F.sum(F.when(merged, F.col("nr") + F.col("nh"))), F.lit(0)).alias("completion_steps"))
    counted = ["indexed", "scanned", "candidates", "completed", "completion_steps"]
    return floors.join(visits, "rb", "left").join(done, "rb", "left").fillna(0, counted).select("rb", "block_floor", *counted)
