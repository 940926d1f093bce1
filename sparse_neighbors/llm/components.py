"""Connected components of an edge list by alternating star contractions.

Every step is a grouped minimum with map-side combine and an equi-join whose other side has one row a
key, so a hub with a third of all edges is combined early or split by the skew-join rule. Nothing but
two numbers a round reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import discard, materialize


def _towards_minimum(edges: DataFrame, larger_only: bool) -> DataFrame:
    """edges (u, v): link neighbours of u to the smallest node around u; larger_only keeps neighbours above u."""
    least = edges.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))
    moved = edges.join(least, "u").where("v > u" if larger_only else "true").select(F.col("v").alias("u"), F.col("low").alias("v"))
    if not larger_only:
        moved = moved.unionByName(least.select("u", F.col("low").alias("v")))
    return moved.where("u <> v").distinct()


def connected_components(edges: DataFrame) -> DataFrame:
    """edges (u, v) of longs -> (node, component), component being the smallest node reachable.

    Only nodes that occur in an edge between different nodes are returned. Nulls and loops are ignored,
    repeated and reversed edges count once; an empty edge list gives an empty result.
    """
    now = edges.where("u is not null and v is not null and u <> v")
    now = materialize(now.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    while True:
        # stars: every node has one parent, and no parent has a parent
        parents = now.groupBy("u").agg(F.count("*").alias("n"))
        many = parents.where("n > 1").limit(1).count()
        if not many and not now.join(now.select(F.col("u").alias("v")), "v", "left_semi").limit(1).count():
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _towards_minimum(both, larger_only=True)
        small = _towards_minimum(large, larger_only=False)
        after = materialize(small, "edges")
        discard(now)
        now = after
    roots = now.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
