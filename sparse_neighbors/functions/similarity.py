"""Dot products: a sorted merge as one Catalyst expression, a map probe, an Arrow kernel and a join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def merge_dot(a: Column, b: Column, kind: str = "bigint") -> Column:
    """Dot product of two packed arrays sorted by d, walking both at once."""
    steps = F.when((F.size(a) > 0) & (F.size(b) > 0), F.sequence(F.lit(1), F.size(a) + F.size(b))).otherwise(F.array().cast("array<int>"))
    begin = F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(0).cast(kind).alias("sum"))

    def walk(state: Column, _: Column) -> Column:
        i, j, total = state["i"], state["j"], state["sum"]
        x, y = F.get(a, i), F.get(b, j)
        same = x["d"] == y["d"]
        return F.when((i >= F.size(a)) | (j >= F.size(b)), state).otherwise(
            F.struct(
                F.when(x["d"] <= y["d"], i + 1).otherwise(i).alias("i"),
                F.when(y["d"] <= x["d"], j + 1).otherwise(j).alias("j"),
                F.when(same, total + (x["w"] * y["w"]).cast(kind)).otherwise(total).alias("sum"),
            )
        )

    return F.aggregate(steps, begin, walk, lambda s: s["sum"])


def probe_dot(a: Column, b: Column, kind: str = "bigint") -> Column:
    """Dot product by looking the features of packed b up in map a; for small maps, whose look-up is linear."""
    return F.aggregate(b, F.lit(0).cast(kind), lambda total, x: total + F.coalesce(F.try_element_at(a, x["d"]) * x["w"], F.lit(0)).cast(kind))


def _merge_arrays(a: pa.Array, b: pa.Array) -> pa.Array:
    out = []
    for x, y in zip(a, b, strict=True):
        dx, dy = (np.asarray(v.values.field("d")) for v in (x, y))
        wx, wy = (np.asarray(v.values.field("w")) for v in (x, y))
        _, i, j = np.intersect1d(dx, dy, assume_unique=True, return_indices=True)
        out.append(int(np.dot(wx[i].astype(np.int64), wy[j].astype(np.int64))))
    return pa.array(out, pa.int64())


def merge_dot_arrow(a: str, b: str) -> Column:
    """Dot product of packed columns with whole weights and numeric dimensions, by sorted intersection in Arrow batches."""

    def run(x: pa.Array, y: pa.Array) -> pa.Array:
        return _merge_arrays(x, y)

    return F.arrow_udf(run, "bigint")(a, b)


def join_dot(r: DataFrame, s: DataFrame) -> DataFrame:
    """(r_id, s_id, score) of all pairs that share a dimension; products are added where they arise, then by pair."""
    left = r.select(F.col("id").alias("r_id"), "d", F.col("w").alias("rw"))
    right = s.select(F.col("id").alias("s_id"), "d", F.col("w").alias("sw"))
    return left.join(right, "d").groupBy("r_id", "s_id").agg(F.sum(F.col("rw") * F.col("sw")).alias("score"))
