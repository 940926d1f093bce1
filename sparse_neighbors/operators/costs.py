"""Work of the methods, counted in closed form from sizes and dimension frequencies."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import vector_sizes
from ..sources.scratch import materialize

#: Over the columns of `summary`.
C2 = "n_s * r_features + n_r * s_features"
C3 = "s_features + products"
MOST_PAIRS = 5_000_000  # postings visited below which pairs are told apart by a shuffle; beyond, they are counted in cells


def cost_pair(r: DataFrame, s: DataFrame) -> DataFrame:
    """Steps to merge each pair: the sum of both sizes."""
    a = vector_sizes(r).select(F.col("id").alias("r_id"), F.col("n_features").alias("nr"))
    b = vector_sizes(s).select(F.col("id").alias("s_id"), F.col("n_features").alias("ns"))
    return a.crossJoin(b).select("r_id", "s_id", (F.col("nr") + F.col("ns")).alias("steps"))


def totals(v: DataFrame, prefix: str) -> DataFrame:
    return v.agg(F.countDistinct("id").alias(f"n_{prefix}"), F.count("*").alias(f"{prefix}_features"))


def products(r: DataFrame, s: DataFrame) -> DataFrame:
    """Postings visited: per dimension, its frequency in R times that in S."""
    a, b = (v.groupBy("d").agg(F.count("*").alias(n)) for v, n in ((r, "fr"), (s, "fs")))
    return a.join(b, "d").agg(F.coalesce(F.sum(F.col("fr") * F.col("fs")), F.lit(0)).alias("products"))


def summary(r: DataFrame, s: DataFrame) -> DataFrame:
    """One row: vectors and features of both sides and the postings visited."""
    return totals(r, "r").crossJoin(totals(s, "s")).crossJoin(products(r, s))


def cost_exhaustive(r: DataFrame, s: DataFrame) -> DataFrame:
    """All pairs merged: |S| times R's features plus |R| times S's."""
    return summary(r, s).select(F.expr(C2).alias("c2"))


def cost_inverted(r: DataFrame, s: DataFrame) -> DataFrame:
    """Postings built plus postings visited."""
    return summary(r, s).select("s_features", "products", F.expr(C3).alias("c3"))


def cost_exhaustive_blocked(r: DataFrame, s: DataFrame) -> DataFrame:
    """Per pair of blocks; r has rb, s has sb."""
    a = r.groupBy("rb").agg(F.countDistinct("id").alias("n_r"), F.count("*").alias("r_features"))
    b = s.groupBy("sb").agg(F.countDistinct("id").alias("n_s"), F.count("*").alias("s_features"))
    return a.crossJoin(b).select("rb", "sb", F.expr(C2).alias("c2"))


def cost_inverted_blocked(r: DataFrame, s: DataFrame) -> DataFrame:
    """Per pair of blocks; lists are built anew for every R-block."""
    a = r.groupBy("rb", "d").agg(F.count("*").alias("fr"))
    b = s.groupBy("sb", "d").agg(F.count("*").alias("fs"))
    visits = a.join(b, "d").groupBy("rb", "sb").agg(F.sum(F.col("fr") * F.col("fs")).alias("products"))
    cells = r.select("rb").distinct().crossJoin(s.groupBy("sb").agg(F.count("*").alias("s_features")))
    return cells.join(visits, ["rb", "sb"], "left").withColumn("products", F.coalesce("products", F.lit(0))).select("rb", "sb", "s_features", "products", F.expr(C3).alias("c3"))


def cost_pruned(r: DataFrame, split: DataFrame) -> DataFrame:
    """Of one S-block: features indexed and postings visited per R-block; r (rb, r_id, d, w), split from `split_features`."""
    fr = r.groupBy("rb", "d").agg(F.count("*").alias("fr"))
    tail = split.where("is_tail")
    return tail.join(fr, ["rb", "d"], "left").groupBy("rb").agg(F.count("*").alias("indexed_features"), F.coalesce(F.sum("fr"), F.lit(0)).alias("scanned_postings"))


def cost_completion(r: DataFrame, split: DataFrame) -> DataFrame:
    """Of one S-block: per R-block, pairs that share an indexed feature, and the steps to merge r with the head of s for those that have one."""
    from .inverted import cells
    from .tail_cells import tail_counts

    split = materialize(split.select("rb", "s_id", "d", "is_tail"), "split")  # read twice, and for the grid before it
    grid = cells(r.withColumnRenamed("r_id", "id"), split.where("is_tail").withColumnRenamed("s_id", "id"), MOST_PAIRS)
    if grid:
        one = F.lit(1).cast("bigint")  # weights don't count here
        return tail_counts(r.withColumn("w", one), split.withColumn("w", one).withColumn("head_bound", F.lit(0)), None, grid).select("rb", "candidates", "completion_steps")
    tails = split.where("is_tail").select("rb", "s_id", "d")
    pairs = r.select("rb", "r_id", "d").join(tails, ["rb", "d"]).select("rb", "r_id", "s_id").distinct()
    sizes = r.groupBy("rb", "r_id").agg(F.count("*").alias("nr"))
    heads = split.where("not is_tail").groupBy("rb", "s_id").agg(F.count("*").alias("nh"))
    steps = F.coalesce(F.col("nr") + F.col("nh"), F.lit(0))
    return pairs.join(sizes, ["rb", "r_id"]).join(heads, ["rb", "s_id"], "left").groupBy("rb").agg(F.count("*").alias("candidates"), F.sum(steps).alias("completion_steps"))
