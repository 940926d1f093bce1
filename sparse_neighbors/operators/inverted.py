"""The inverted join: scores are added up over posting lists, so only shared dimensions cost anything."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.similarity import join_dot
from .costs import summary
from .exhaustive import cell_join, cell_scores
from .pair_cells import pair_scores
from .topk import top_k

R_CELL, S_CELL = 1 << 18, 1 << 20  # features of a side in one cell
MOST_SUMS = 50_000_000  # postings visited below which partial sums are shuffled by pair


def posting_lists(s: DataFrame, packed: bool = False) -> DataFrame:
    """Posting lists of S: rows (d, s_id, w) clustered by d, or one row per d."""
    rows = s.select("d", F.col("id").alias("s_id"), "w")
    if packed:
        return rows.groupBy("d").agg(F.collect_list(F.struct("s_id", "w")).alias("postings"))
    return rows.repartition("d").sortWithinPartitions("d")


def accumulate(r: DataFrame, lists: DataFrame, keys: tuple[str, ...] = (), by: tuple[str, ...] = ()) -> DataFrame:
    """r (keys, by, r_id, d, w) against lists (keys, d, s_id, w): sums of products per pair; `by` are more columns of r to keep."""
    left = r.withColumnRenamed("w", "rw")
    right = lists.withColumnRenamed("w", "sw")
    joined = left.join(right, [*keys, "d"])
    return joined.groupBy(*keys, *by, "r_id", "s_id").agg(F.sum(F.col("rw") * F.col("sw")).alias("score"))


def cells(r: DataFrame, s: DataFrame, most: int | None = None) -> tuple[int, int] | None:
    """(R-blocks, S-blocks) if a grid of cells moves fewer rows than there can be partial sums, which then aren't shuffled; else none."""
    n = summary(r, s).first()
    nr, ns = max(1, -(-n["r_features"] // R_CELL)), max(1, -(-n["s_features"] // S_CELL))
    moved = n["r_features"] * ns + n["s_features"] * nr
    return (nr, ns) if n["products"] > max(MOST_SUMS if most is None else most, 2 * moved) else None


def inverted_join(r: DataFrame, s: DataFrame, k: int = 5, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """The whole-set form in one job: an equi-join on d, partial sums before the shuffle, a limit per r before the last one.

    Where many pairs share frequent dimensions, nearly every product is a partial sum of its own; lists are then added up in cells.
    """
    grid = cells(r, s)
    if grid:
        return cell_join(r, s, k, *grid, ties, exclude_self)
    scores = join_dot(r, s)
    if exclude_self:
        scores = scores.where("r_id <> s_id")
    return top_k(scores, k, ties)


def candidate_scores(r: DataFrame, s: DataFrame, k: int) -> DataFrame:
    """Scores (r_id, s_id, score) that hold the k best of each r: of all pairs, or k per r of each cell where `inverted_join` takes cells."""
    grid = cells(r, s)
    return cell_scores(r, s, k, *grid) if grid else join_dot(r, s)


def every_score(r: DataFrame, s: DataFrame) -> DataFrame:
    """Scores (r_id, s_id, score) of all pairs that share a dimension; streamed out of cells where partial sums would outgrow a shuffle."""
    grid = cells(r, s)
    return pair_scores(r, s, for_tasks(r, grid)) if grid else join_dot(r, s)


def for_tasks(r: DataFrame, grid: tuple[int, int]) -> tuple[int, int]:
    """The grid with as many S-blocks as give every task a cell."""
    tasks = int(r.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return grid[0], max(grid[1], -(-tasks // grid[0]))


def inverted_packed(r: DataFrame, s: DataFrame, k: int = 5, heavy: int = 10_000, ties: str = "id", exclude_self: bool = False) -> DataFrame:
    """Lists of up to `heavy` postings travel as one row; longer ones stay rows, so no list is one large value."""
    freq = s.groupBy("d").agg(F.count("*").alias("freq"))
    left = r.select(F.col("id").alias("r_id"), "d", F.col("w").alias("rw"))
    light = posting_lists(s.join(freq.where(F.col("freq") <= heavy), "d", "left_semi"), packed=True)
    short = left.join(light, "d").select("r_id", "rw", F.inline("postings")).select("r_id", "s_id", (F.col("rw") * F.col("w")).alias("product"))
    long = left.join(s.join(freq.where(F.col("freq") > heavy), "d", "left_semi").select("d", F.col("id").alias("s_id"), "w"), "d").select("r_id", "s_id", (F.col("rw") * F.col("w")).alias("product"))
    products = short.unionByName(long)
    if exclude_self:
        products = products.where("r_id <> s_id")
    return top_k(products.groupBy("r_id", "s_id").agg(F.sum("product").alias("score")), k, ties)


def write_index(s: DataFrame, path: str, buckets: int = 16) -> None:
    """Posting lists as Parquet, partitioned by a hash bucket of d and sorted by d in each file."""
    rows = s.select("d", F.col("id").alias("s_id"), "w").withColumn("bucket", F.pmod(F.xxhash64("d"), F.lit(buckets)).cast("int"))
    rows.repartition(buckets, "bucket").sortWithinPartitions("bucket", "d").write.mode("overwrite").partitionBy("bucket").parquet(path)


def read_index(spark, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("bucket")
