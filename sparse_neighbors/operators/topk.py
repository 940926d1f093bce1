"""Candidate sets: the k best rows of each r, their k-th scores, and other shapes of the result."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TIES = ("id", "all", "strict")


def top_k(scores: DataFrame, k: int, ties: str = "id", keys: tuple[str, ...] = ("r_id",)) -> DataFrame:
    """scores (keys, s_id, score) -> the k best by score, then s_id, with their rank.

    ties: "id" keeps at most k rows; "all" keeps every row that ties with the k-th; "strict" drops a group of equal
    scores that crosses k. The first two are ranks with a limit, which Spark applies before it shuffles.
    """
    best = Window.partitionBy(*keys).orderBy(F.col("score").desc(), F.col("s_id"))
    if ties == "id":
        return scores.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    group = Window.partitionBy(*keys).orderBy(F.col("score").desc())
    ranked = scores.withColumn("rank", F.rank().over(group)).where(F.col("rank") <= k)
    if ties == "all":
        return ranked
    if ties == "strict":
        equal = Window.partitionBy(*keys, "score")
        return ranked.withColumn("equal", F.count("*").over(equal)).where(F.col("rank") + F.col("equal") - 1 <= k).drop("equal")
    raise ValueError(f"ties must be one of {TIES}")


def kth_scores(candidates: DataFrame, outer: DataFrame, k: int) -> DataFrame:
    """outer (rb, r_id) plus kth_score: the k-th best score so far, 0 while there are fewer than k."""
    best = Window.partitionBy("rb", "r_id").orderBy(F.col("score").desc(), F.col("s_id"))
    kth = candidates.withColumn("rank", F.row_number().over(best)).where(F.col("rank") == k).select("rb", "r_id", F.col("score").alias("kth_score"))
    return outer.join(kth, ["rb", "r_id"], "left").withColumn("kth_score", F.coalesce("kth_score", F.lit(0)))


def to_nested(result: DataFrame) -> DataFrame:
    """One row per r with its neighbours in rank order."""
    one = F.struct("rank", "s_id", "score")
    return result.groupBy("r_id").agg(F.array_sort(F.collect_list(one)).alias("neighbours"))


def to_best(result: DataFrame) -> DataFrame:
    """One row per r with its candidates as an array that sorts by falling score, then s_id."""
    return result.groupBy("r_id").agg(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("below"), "s_id"))).alias("best"))


def merge_best(a, b, k: int):
    """The k best of two such arrays as a column, for states that are kept as arrays; a null array is empty."""
    empty = F.slice(F.coalesce(a, b), 1, 0)
    return F.slice(F.array_sort(F.concat(F.coalesce(a, empty), F.coalesce(b, empty))), 1, k)


def from_best(nested: DataFrame) -> DataFrame:
    """r_id, best -> r_id, s_id, score, rank."""
    return nested.select("r_id", F.posexplode("best").alias("place", "x")).select("r_id", F.col("x.s_id").alias("s_id"), (-F.col("x.below")).alias("score"), (F.col("place") + 1).cast("int").alias("rank"))


def fill_zero(result: DataFrame, r: DataFrame, s: DataFrame, k: int, exclude_self: bool = False) -> DataFrame:
    """Pads r with fewer than k neighbours by the s of lowest id that it has no score with; never by itself with exclude_self.

    At most 2k lowest ids can be needed, so the padding side is that small.
    """
    lowest = s.select(F.col("id").alias("s_id")).distinct().orderBy("s_id").limit(2 * k)
    have = result.groupBy("r_id").agg(F.count("*").alias("n"))
    ids = r.select(F.col("id").alias("r_id")).distinct().join(have, "r_id", "left").withColumn("n", F.coalesce("n", F.lit(0))).where(F.col("n") < k)
    pads = ids.join(F.broadcast(lowest)).join(result.select("r_id", "s_id"), ["r_id", "s_id"], "left_anti")
    if exclude_self:
        pads = pads.where("r_id <> s_id")
    place = Window.partitionBy("r_id").orderBy("s_id")
    pads = pads.withColumn("rank", (F.col("n") + F.row_number().over(place)).cast("int")).where(F.col("rank") <= k)
    return result.unionByName(pads.select("r_id", "s_id", F.lit(0).cast(result.schema["score"].dataType).alias("score"), "rank"))
