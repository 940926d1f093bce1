"""Block plans: how many pages and blocks R and S take under a buffer, and which vector is in which block."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import discard, materialize

FEATURE_BYTES = 12


@dataclass(frozen=True)
class BlockPlan:
    r_pages: int
    s_pages: int
    r_blocks: int
    s_blocks: int

    @property
    def io_pages(self) -> int:
        """Pages read by a block nested loop: R once, S once per R-block."""
        return self.r_pages + self.r_blocks * self.s_pages


def plan_sizes(r_features: int, s_features: int, buffer_fraction: float = 0.5, r_share: float = 0.8, page_bytes: int = 8192, layout: str = "split") -> BlockPlan:
    """Defaults: a buffer of half of R and S, four fifths of it for R, pages of 8192 bytes.

    layout "split" gives R and S shares of the buffer; "classic" keeps one page for S and one for output.
    """
    pages = [max(1, math.ceil(n * FEATURE_BYTES / page_bytes)) for n in (r_features, s_features)]
    buffer = max(2, math.ceil(sum(pages) * buffer_fraction))
    if layout == "classic":
        r_buffer, s_buffer = max(1, buffer - 2), 1
    else:
        r_buffer = max(1, math.floor(buffer * r_share))
        s_buffer = max(1, buffer - r_buffer)
    return BlockPlan(pages[0], pages[1], math.ceil(pages[0] / r_buffer), math.ceil(pages[1] / s_buffer))


def plan_blocks(r: DataFrame, s: DataFrame, **settings) -> BlockPlan:
    return plan_sizes(r.count(), s.count(), **settings)


def assign_blocks(v: DataFrame, n: int, how: str = "range", column: str = "block") -> DataFrame:
    """v plus its block number.

    range: ascending runs of ids with about equal numbers of features (two-level sums, no single-task sort); mod, hash: by
    id; geometric: runs whose sizes double, the first being small. A run is known by its first id, so v itself isn't shuffled.
    """
    if how == "mod":
        return v.withColumn(column, F.pmod(F.col("id"), F.lit(n)).cast("int"))
    if how == "hash":
        return v.withColumn(column, F.pmod(F.xxhash64("id"), F.lit(n)).cast("int"))
    if how not in ("range", "geometric"):
        raise ValueError(how)
    # written before partition numbers are read from it twice, so that both readings see the same partitions
    sizes = materialize(v.groupBy("id").agg(F.count("*").alias("size")), "sizes")
    numbered = materialize(sizes.repartitionByRange("id").withColumn("part", F.spark_partition_id()), "sizes")
    discard(sizes)
    sizes = numbered
    parts = sizes.groupBy("part").agg(F.sum("size").alias("all"))
    parts = parts.withColumn("base", F.coalesce(F.sum("all").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("total", F.sum("all").over(Window.partitionBy()))
    own = Window.partitionBy("part").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    placed = sizes.withColumn("before", F.coalesce(F.sum("size").over(own), F.lit(0))).join(F.broadcast(parts.select("part", "base", "total")), "part")  # a row a partition
    share = (F.col("base") + F.col("before")) / F.col("total")
    if how == "range":
        block = F.floor(share * n)
    else:  # block i begins at (2^i - 1) / (2^n - 1)
        block = F.floor(F.log2(share * (2**n - 1) + 1))
    blocks = placed.select("id", F.least(block, F.lit(n - 1)).cast("int").alias(column))
    starts = blocks.groupBy(column).agg(F.min("id").alias("first")).collect()  # a row a block
    starts.sort(key=lambda x: x["first"])
    discard(numbered)
    if not starts:
        return v.withColumn(column, F.lit(0))
    first, number = (F.array(*(F.lit(x[c]) for x in starts)) for c in ("first", column))
    return v.withColumn(column, F.get(number, F.greatest(F.size(F.filter(first, lambda x: x <= F.col("id"))) - 1, F.lit(0))))
