"""Mixing sources to target weights, with DataFrame functions only.

Sizes are added up per source. A budget, a share of all sizes, is dealt to the sources by weight; no target
exceeds `most` times its source's size, and what a full source can't take goes to the others by weight until none
is above. Then each document is taken floor(rate) times and once more if a uniform number hashed from its id and a
seed is below the fraction, so reruns agree and no document exceeds `most` times its size (for a whole `most`).

The documents meet their source's rate by a broadcast of one row per source, whose number is checked; beyond
MAX_SOURCES it is a shuffled join that the skew rule splits. Sizes are summed before they are shuffled.

Results for odd input: a null text has size 0; a null source is a source of its own, last in order; a source whose
sizes are all 0 has target 0; documents with the same id are drawn alike, a null id as an empty one; an empty table
gives an empty result; other columns are ignored by `mix_plan` and kept by `mix_documents`.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import materialize

MAX_SOURCES = 100_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def uniform(doc_id: Column, seed: str) -> Column:
    """A number in [0, 1) from the id: 52 bits of an MD5, the same in every engine."""
    digest = F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(seed)))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def source_targets(sizes: DataFrame, weights: Sequence[float], share: float, most: float) -> DataFrame:
    """sizes (source, size) -> source, source_size, target: one row per source.

    Sources are ordered by code point (null last) and take the weights in turn. Filling by weight up to the caps
    stops at one water level. Sorted by cap over weight, with the first k taken as full, the others' level grows with k
    up to the right k and falls from there, so the water level is the largest.
    """
    per_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*(F.lit(float(w)) for w in weights))
    weighed = per_source.withColumn("weight", F.element_at(cycle, (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    weighed = weighed.withColumn("cap", F.lit(most) * F.col("source_size"))
    by_level = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    after = by_level.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy()
    levels = weighed.withColumn("level", (F.lit(share) * F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after))
    water = F.max("level").over(everything)
    return levels.withColumn("water", water).select("source", "source_size", F.least(F.col("cap"), F.col("water") * F.col("weight")).alias("target"))


def _copies(rows: DataFrame, sizes: DataFrame, weights: Sequence[float], share: float, most: float, seed: str) -> DataFrame:
    """rows (doc_id, source, ...) plus source_size, target and copies, at the rates that sizes (source, size) give."""
    targets = materialize(source_targets(sizes, weights, share, most), "targets")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rates = targets.select(F.col("source").alias("_source"), "source_size", "target", rate.alias("_rate"))
    if rates.limit(MAX_SOURCES + 1).count() <= MAX_SOURCES:
        rates = F.broadcast(rates)
    joined = rows.join(rates, rows["source"].eqNullSafe(rates["_source"]), "left")
    extra = F.when(uniform(F.col("doc_id"), seed) < F.col("_rate") - F.floor("_rate"), 1).otherwise(0)
    return joined.withColumn("copies", (F.floor("_rate") + extra).cast("int")).drop("_source", "_rate")


def _sized(docs: DataFrame) -> DataFrame:
    """doc_id, source, size of every document, from one pass over the texts."""
    sizes = docs.select("doc_id", F.col("source").cast("string").alias("source"), word_count(F.col("text").cast("string")).alias("size"))
    return materialize(sizes, "sizes")


def mix_plan(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2, seed: str = ":mix") -> DataFrame:
    """docs (doc_id, text, source) -> doc_id, size, source_size, target, taken."""
    sizes = _sized(docs)
    planned = _copies(sizes, sizes, weights, share, most, seed)
    return planned.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def mix_documents(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2, seed: str = ":mix") -> DataFrame:
    """docs as they are, each row as often as it is taken."""
    rows = docs.select(F.struct(*docs.columns).alias("_row"), "doc_id", F.col("source").cast("string").alias("source"))
    planned = _copies(rows, _sized(docs), weights, share, most, seed)
    return planned.select("_row", F.explode(F.array_repeat(F.lit(0), F.col("copies")))).select("_row.*")
