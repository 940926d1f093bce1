"""The block nested loop: R-blocks side by side, S-blocks one after another, carrying each r's k-th score.

R-blocks are independent, so rb is a column and all of them run in one job. S-blocks follow each other because each
one's pruning needs the scores found before; the state between two is at most k rows per r, written to the shared folder.
If all of R is below RESIDENT_BYTES, it goes to every task, and an S-block is shuffled by s_id only.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import pack
from ..operators.exhaustive import cell_scores, exhaustive_block, guard
from ..operators.inverted import accumulate, cells
from ..operators.pruned import PruneOptions, block_dimstats, first_block_work, pruned_block, pruned_work
from ..operators.resident import RESIDENT_BYTES, feature_bytes
from ..operators.topk import top_k
from ..sources.scratch import discard, materialize
from .blocks import BlockPlan, assign_blocks, plan_blocks

KERNELS = ("exhaustive", "inverted", "pruned")


def keep_best(scores: DataFrame, k: int, ties: str = "id") -> DataFrame:
    """The k best of each r with their rank and, in every row of an r, its k-th score: 0 while there are fewer than k.

    Rows beyond k only tie with the k-th, so the least score is the k-th; it takes the partitioning of the ranks.
    """
    own = Window.partitionBy("rb", "r_id")
    full = F.count("*").over(own) >= k
    return top_k(scores, k, ties, ("rb", "r_id")).withColumn("kth_score", F.when(full, F.min("score").over(own)).otherwise(F.lit(0)))


def thresholds(state: DataFrame, ties: str = "id") -> DataFrame:
    """rb, r_id, kth_score of the vectors that have k candidates; for all others it is 0."""
    kth = state.where("rank = 1 and kth_score > 0").select("rb", "r_id", "kth_score")
    return kth if ties == "id" else kth.dropDuplicates(["rb", "r_id"])


def merge_candidates(old: DataFrame, new: DataFrame, kth: DataFrame, k: int, strict: bool, ties: str = "id") -> DataFrame:
    """The best of old and new; a new pair must beat (strict) or reach its r's k-th score."""
    met = new.join(kth, ["rb", "r_id"], "left").withColumn("kth_score", F.coalesce("kth_score", F.lit(0)))
    better = met.where("score > kth_score" if strict else "score >= kth_score and score > 0").select("rb", "r_id", "s_id", "score")
    return keep_best(old.select("rb", "r_id", "s_id", "score").unionByName(better), k, ties)


def together(*steps):
    """Steps that don't depend on each other, as jobs side by side; each is a function without arguments."""
    with ThreadPoolExecutor(len(steps)) as pool:
        return [f.result() for f in [pool.submit(step) for step in steps]]


def block_join(
    r: DataFrame, s: DataFrame, k: int = 5, kernel: str = "pruned", plan: BlockPlan | None = None, options: PruneOptions = PruneOptions(),
    r_how: str = "range", s_how: str = "range", order: list[int] | None = None, ties: str = "id", exclude_self: bool = False, report: list | None = None, stop_after: int | None = None,
    work: list | None = None, resident_bytes: int = RESIDENT_BYTES,
) -> DataFrame:
    """r, s (id, d, w) -> r_id, s_id, score, rank; `report` receives the candidate state after each S-block.

    `work` receives, for each S-block of the pruned kernel, what each R-block did with it (see `pruned_work`) and sb.

    Strict acceptance depends on S-blocks that ascend by id, so it forces range blocks in ascending order.
    """
    if kernel not in KERNELS:
        raise ValueError(f"kernel must be one of {KERNELS}")
    sides = []
    if plan is None:
        r, s = sides = together(lambda: materialize(r, "side"), lambda: materialize(s, "side"))
        plan = plan_blocks(r, s)
    strict = options.rule == "strict" and kernel == "pruned"
    if strict and (s_how not in ("range", "geometric") or ties != "id" or (order is not None and order != sorted(order))):
        raise ValueError("the strict rule needs ascending id blocks and ties by id")

    def cut(v: DataFrame, blocks: int, how: str, column: str, own: str) -> DataFrame:
        """v in blocks; it is written first, since the bounds of blocks come from its sizes and building vectors costs more than writing them."""
        held = v if blocks == 1 or how in ("mod", "hash") or hasattr(v, "_materialized_at") else materialize(v.select("id", "d", "w"), "side")
        placed = held.withColumn(column, F.lit(0)) if blocks == 1 else assign_blocks(held, blocks, how, column)
        out = materialize(placed.select(column, F.col("id").alias(own), "d", "w"), "blocks", by="sb" if column == "sb" else None)
        if held is not v:
            discard(held)
        return out

    outer, inner = together(lambda: cut(r, plan.r_blocks, r_how, "rb", "r_id"), lambda: cut(s, plan.s_blocks, s_how, "sb", "s_id"))
    kind = r.schema["w"].dataType.simpleString()
    state = held = None
    discard(*sides)
    spent = [outer, inner]
    numbers = list(range(plan.s_blocks) if order is None else order)[:stop_after]
    if not numbers:
        discard(*spent)
        return r.sparkSession.createDataFrame([], f"r_id long, s_id long, score {kind}, rank int")

    resident = kernel != "exhaustive" and feature_bytes(outer) <= resident_bytes

    grid = cells(outer.withColumnRenamed("r_id", "id"), inner.withColumnRenamed("s_id", "id")) if kernel != "exhaustive" else None
    grid = grid and (grid[0], -(-grid[1] // plan.s_blocks))  # of an S-block

    def add_up(block: DataFrame) -> DataFrame:
        if grid:
            found = cell_scores(outer.withColumnRenamed("r_id", "id"), block.withColumnRenamed("s_id", "id"), k, *grid, ties, exclude_self)
            return found.join(outer.select("rb", "r_id").distinct(), "r_id")
        if resident:
            return accumulate(F.broadcast(outer), block.repartition("s_id"), by=("rb",))
        return accumulate(outer, block, by=("rb",))

    def first(new: DataFrame) -> DataFrame:
        new = new.where("score > 0 and r_id <> s_id" if exclude_self else "score > 0")
        return materialize(keep_best(new, k, ties), "candidates")

    if kernel == "pruned":
        # the first block has no floor to prune with, so it needs none of what the later ones do
        block = inner.where(F.col("sb") == numbers[0]).drop("sb")
        rest = inner.where(F.col("sb").isin(numbers[1:])).select("sb", "d").distinct()
        dimstats, packed_r, state, live = together(
            lambda: materialize(block_dimstats(outer, options.dim_order), "dimstats"),
            lambda: materialize(outer.groupBy("rb", "r_id").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("features")), "packed"),
            lambda: first(add_up(block)),
            # the vectors that meet each later S-block, for its floors
            lambda: materialize(rest.join(F.broadcast(outer.select("rb", "r_id", "d")) if resident else outer.select("rb", "r_id", "d"), "d").select("sb", "rb", "r_id").distinct(), "live"),
        )
        spent += [dimstats, packed_r, live]
        if work is not None:
            work.append(materialize(first_block_work(outer, block, grid).withColumn("sb", F.lit(numbers[0])), "work"))
        if report is not None:
            report.append(state)
        held, numbers = state, numbers[1:]
    elif kernel == "exhaustive":
        guard(outer.withColumnRenamed("r_id", "id"), inner.withColumnRenamed("s_id", "id"))
        packed_r = pack(outer.select(F.struct("rb", "r_id").alias("id"), "d", "w")).select("id.rb", "id.r_id", "features")
    for number in numbers:
        block = inner.where(F.col("sb") == number).drop("sb")
        kth = thresholds(state, ties) if state is not None else None
        if kernel == "exhaustive":
            new = exhaustive_block(packed_r, pack(block.withColumnRenamed("s_id", "id")).withColumnRenamed("id", "s_id"), kind)
        elif kernel == "pruned":
            new = pruned_block(outer, block, kth, dimstats, options, packed_r, live.where(F.col("sb") == number).drop("sb"), resident, work is not None if grid else not resident or work is not None, grid, k, ties, exclude_self)
        else:
            new = add_up(block)
        written = getattr(new, "_written", None)
        if work is not None and kernel == "pruned":
            work.append(materialize(pruned_work(outer, written, kth, new._floors, options, grid).withColumn("sb", F.lit(number)), "work"))
        if exclude_self:
            new = new.where("r_id <> s_id")
        after = first(new) if state is None else materialize(merge_candidates(state, new, kth, k, strict, ties), "candidates")
        if written is not None:
            discard(written)
        if report is not None:
            report.append(after)
        elif held is not None:
            discard(held)
        state = held = after
    discard(*spent)
    return state.select("r_id", "s_id", "score", "rank")  # a vector of R is in one block only, so ranks hold


def join_report(r: DataFrame, s: DataFrame, k: int = 5, plan: BlockPlan | None = None, options: PruneOptions = PruneOptions()) -> DataFrame:
    """What the pruned join does, a row per S-block and R-block that meets it: sb, rb, block_floor, indexed, scanned, candidates, completed, completion_steps."""
    work: list[DataFrame] = []
    block_join(r, s, k, "pruned", plan, options, work=work)
    out = work[0]
    for x in work[1:]:
        out = out.unionByName(x)
    return out
