"""One entry for all methods, with a choice of strategy from exact statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import reweight
from ..operators import costs
from ..operators.exhaustive import exhaustive_grid, exhaustive_join
from ..operators.inverted import inverted_join, inverted_packed
from ..operators.pruned import PruneOptions
from ..operators.resident import RESIDENT_BYTES, ROW_BYTES, resident_join
from ..operators.topk import fill_zero as pad
from .blocks import FEATURE_BYTES, BlockPlan, plan_blocks
from .nested_loop import block_join

PARTIAL_SUM_BYTES = 24
STRATEGIES = ("auto", "dimension", "resident")
MOST_SCANS = 16  # of S that the resident form may take, a scan for each broadcast block of R


def _choice(n) -> tuple[str, str]:
    """(method, strategy) from the row of `costs.summary`."""
    sums = n["products"] * PARTIAL_SUM_BYTES
    scans = max(1, -(-n["r_features"] * ROW_BYTES // RESIDENT_BYTES))
    if n["s_features"] < 10_000_000 or sums <= 4 * scans * n["s_features"] * FEATURE_BYTES:
        return "inverted", "dimension"
    return ("inverted", "resident") if scans <= MOST_SCANS else ("pruned", "dimension")


def choose_strategy(r: DataFrame, s: DataFrame) -> tuple[str, str]:
    """(method, strategy) that moves the fewest bytes.

    One shuffle by dimension while its partial sums stay below repeated scans of S; then S in place with blocks of R broadcast, if
    MOST_SCANS of them hold R; then the pruned loop.
    """
    return _choice(costs.summary(r, s).first())


def knn_join(
    r: DataFrame, s: DataFrame, k: int = 5, method: str = "auto", metric: str = "dot", ties: str = "id", exclude_self: bool = False,
    fill_zero: bool = False, plan: BlockPlan | None = None, options: PruneOptions = PruneOptions(), blocked: bool | None = None, strategy: str = "auto",
) -> DataFrame:
    """For every r the k vectors of s with the largest positive score: r_id, s_id, score, rank.

    method: pruned (block nested loop), inverted, packed, exhaustive, grid or auto; blocked forces the loop for the others.
    strategy, of the inverted method: dimension (both sides are shuffled by dimension), resident (S stays in place, blocks of R are
    broadcast) or auto, which leaves a method that was named in its form by dimension.
    metric: dot, or cosine (dot of unit vectors). Pairs with score 0 are returned only as padding with fill_zero.
    """
    if metric == "cosine":
        r, s = reweight(r, "l2"), reweight(s, "l2")
    elif metric != "dot":
        raise ValueError(metric)
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy must be one of {STRATEGIES}")
    if strategy == "resident" and (method not in ("auto", "inverted") or blocked):
        raise ValueError("the resident strategy belongs to the inverted method")
    if method == "auto" and strategy == "resident":
        method = "inverted"
    elif method == "auto":
        method, found = choose_strategy(r, s)
        strategy = found if strategy == "auto" else strategy
    inner = "all" if ties == "strict" and (method == "pruned" or blocked) else ties
    if method == "pruned" or blocked:
        out = block_join(r, s, k, method, plan, options, ties=inner, exclude_self=exclude_self)
        if ties == "strict":  # filtered at the end: a group dropped early would lower later thresholds
            from pyspark.sql import Window

            equal = F.count("*").over(Window.partitionBy("r_id", "score"))
            out = out.withColumn("equal", equal).where(F.col("rank") + F.col("equal") - 1 <= k).drop("equal")
    elif method == "inverted" and strategy == "resident":
        out = resident_join(r, s, k, ties, exclude_self)
    elif method == "inverted":
        out = inverted_join(r, s, k, ties, exclude_self)
    elif method == "packed":
        out = inverted_packed(r, s, k, ties=ties, exclude_self=exclude_self)
    elif method == "exhaustive":
        out = exhaustive_join(r, s, k, ties, exclude_self)
    elif method == "grid":
        out = exhaustive_grid(r, s, k, ties=ties, exclude_self=exclude_self)
    else:
        raise ValueError(method)
    return pad(out, r, s, k, exclude_self) if fill_zero else out


def explain_join(r: DataFrame, s: DataFrame) -> DataFrame:
    """What each method would cost and which one `auto` takes."""
    plan, (method, _) = plan_blocks(r, s), choose_strategy(r, s)
    named = costs.summary(r, s).withColumn("c2", F.expr(costs.C2)).withColumn("c3", F.expr(costs.C3))
    return named.select(F.lit(method).alias("method"), "c2", "c3", (F.col("products") * PARTIAL_SUM_BYTES).alias("shuffle_bytes"), F.lit(plan.io_pages).alias("pages"), F.lit(plan.r_blocks).alias("r_blocks"), F.lit(plan.s_blocks).alias("s_blocks"))
