"""The resident form of the inverted join: S stays where its vectors are, and blocks of R go to every task.

S is hash-partitioned by id per block, without the dimensions that R lacks. All partial sums of a pair then arise in one partition,
so none are shuffled; what moves besides are the blocks of R, each below a checked size, and k rows per r and task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.blocks import assign_blocks
from ..sources.scratch import collect_garbage, discard, materialize
from .inverted import accumulate
from .topk import top_k

RESIDENT_BYTES = 64 << 20  # of features of R in one broadcast, before hashing
ROW_BYTES = 32
MOST_SCANS = 16  # of S, unless blocks of RESIDENT_BYTES need more


def feature_bytes(v: DataFrame) -> int:
    """Size of a vector set's features as rows, from all of them."""
    texts = F.octet_length("d").cast("long") if v.schema["d"].dataType.simpleString() == "string" else F.lit(0)
    return v.agg(F.coalesce(F.sum(texts + ROW_BYTES), F.lit(0)).alias("bytes")).first()["bytes"]


def resident_join(r: DataFrame, s: DataFrame, k: int = 5, ties: str = "id", exclude_self: bool = False, block_bytes: int = RESIDENT_BYTES) -> DataFrame:
    """r_id, s_id, score, rank like `inverted_join`; R beyond block_bytes is cut into blocks of ids, and S is read once per block.

    Blocks smaller than RESIDENT_BYTES are merged where more than MOST_SCANS would be needed. S is written once, and blocks follow each
    other, each with its result written, so that the driver holds one broadcast at a time. A single vector of R larger than a block
    is a block of its own size.
    """
    s = s.select("id", "d", "w")
    r = materialize(r.select("id", "d", "w"), "outer")
    blocks = block_count(feature_bytes(r), block_bytes)

    def near(part: DataFrame) -> DataFrame:
        met = s.join(F.broadcast(part.select("d").distinct()), "d", "left_semi").repartition("id")
        scores = accumulate(F.broadcast(part.withColumnRenamed("id", "r_id")), met.withColumnRenamed("id", "s_id"))
        return top_k(scores.where("score > 0 and r_id <> s_id" if exclude_self else "score > 0"), k, ties)

    if blocks == 1:
        return near(r)
    s = materialize(s, "inner")
    cut = materialize(assign_blocks(r, blocks, "range", "rb"), "outer", by="rb")
    discard(r)
    out = None
    for n in range(blocks):
        best = materialize(near(cut.where(F.col("rb") == n).drop("rb")), "near")
        out = best if out is None else out.unionByName(best)
        collect_garbage(r.sparkSession)
    discard(cut, s)
    return out


def block_count(size: int, block_bytes: int) -> int:
    """Blocks of R of `size` bytes."""
    wanted = -(-size // block_bytes)
    return max(1, wanted if block_bytes >= RESIDENT_BYTES else max(min(wanted, MOST_SCANS), -(-size // RESIDENT_BYTES)))
