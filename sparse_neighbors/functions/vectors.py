"""Sparse vectors as DataFrames: long form (id, d, w), one row a feature; packed form (id, features sorted by d)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SEPARATORS = r"[ \n\t\r]+"


def from_long(df: DataFrame, id: str | Column, dim: str | Column, weight: str | Column, merge: str = "sum") -> DataFrame:
    """Long vectors; features of one id and dimension are merged by sum or max, and zeros are no features."""
    rows = df.select(F.col(id).alias("id") if isinstance(id, str) else id.alias("id"), F.col(dim).alias("d") if isinstance(dim, str) else dim.alias("d"), F.col(weight).alias("w") if isinstance(weight, str) else weight.alias("w"))
    merged = {"sum": F.sum, "max": F.max}[merge]("w")
    return rows.groupBy("id", "d").agg(merged.alias("w")).where("id is not null and d is not null and w > 0")


def counted(df: DataFrame) -> DataFrame:
    """Whole weights as BIGINT, so that scores are exact."""
    return df.withColumn("w", F.col("w").cast("bigint"))


def pack(df: DataFrame) -> DataFrame:
    return df.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("features"))


def unpack(df: DataFrame) -> DataFrame:
    return df.select("id", F.inline("features"))


def as_map(df: DataFrame) -> DataFrame:
    return df.select("id", F.map_from_entries("features").alias("features"))


def from_text(df: DataFrame, id: str, text: str) -> DataFrame:
    """Counts of lower-cased tokens; the dimension is the token."""
    tokens = df.select(F.col(id).alias("id"), F.explode(F.split(F.lower(F.col(text)), SEPARATORS)).alias("d")).where("d <> ''")
    return tokens.groupBy("id", "d").agg(F.count("*").alias("w"))


def dimension_dictionary(df: DataFrame) -> DataFrame:
    """(d, number): dense numbers in order of d, from partition offsets rather than one global window."""
    terms = df.select("d").distinct().repartitionByRange("d").withColumn("part", F.spark_partition_id())
    own = Window.partitionBy("part").orderBy("d")
    offsets = terms.groupBy("part").agg(F.count("*").alias("n")).withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    numbered = terms.withColumn("place", F.row_number().over(own)).join(F.broadcast(offsets.select("part", "base")), "part")  # one row a partition
    return numbered.select("d", (F.col("base") + F.col("place") - 1).alias("number"))


def from_peaks(df: DataFrame, id: str | Column, x: str, intensity: str | Column, scale: int = 10, merge: str = "sum") -> DataFrame:
    """Peaks binned to floor(scale * x); intensities in one bin are merged."""
    return from_long(df, id, F.floor(F.col(x) * scale).cast("bigint"), intensity, merge)


def from_dense(df: DataFrame, id: str, array: str, scale: int = 1000) -> DataFrame:
    """The positive part of dense vectors, in whole units of 1 / scale."""
    rows = df.select(F.col(id).alias("id"), F.posexplode(array).alias("d", "x"))
    return rows.select("id", F.col("d").cast("bigint").alias("d"), F.round(F.col("x").cast("double") * scale).cast("bigint").alias("w")).where("w > 0")


def vector_sizes(v: DataFrame) -> DataFrame:
    return v.groupBy("id").agg(F.count("*").alias("n_features"), F.sum("w").alias("total_weight"), F.max("w").alias("max_weight"))


def dimension_stats(v: DataFrame, by: str | None = None) -> DataFrame:
    keys = [by, "d"] if by else ["d"]
    return v.groupBy(*keys).agg(F.count("*").alias("freq"), F.max("w").alias("peak_weight"))


def sparsity(v: DataFrame) -> DataFrame:
    return v.agg(F.countDistinct("id").alias("n_vectors"), F.countDistinct("d").alias("n_dims"), F.count("*").alias("n_features"))


def validate_vectors(v: DataFrame, on_negative: str = "error") -> DataFrame:
    """v without zeros; negative, non-finite or repeated features are an error, or negatives are clipped away.

    The pruning bound holds for positive weights only, so this is a hard contract.
    """
    w = F.col("w").cast("double")
    bad = w.isNull() | F.isnan(w) | (F.abs(w) == float("inf")) | F.col("id").isNull() | F.col("d").isNull()
    if on_negative == "error":
        bad = bad | (w < 0)
    if v.where(bad).limit(1).count():
        raise ValueError("vectors hold null, non-finite or negative features")
    if v.groupBy("id", "d").agg(F.count("*").alias("n")).where("n > 1").limit(1).count():
        raise ValueError("a vector holds a dimension twice")
    return v.where("w > 0")


def reweight(v: DataFrame, how: str = "raw") -> DataFrame:
    """raw, l2 (unit length; the dot product is then the cosine) or tfidf."""
    if how == "raw":
        return v
    if how == "l2":
        norms = v.groupBy("id").agg(F.sqrt(F.sum(F.col("w").cast("double") * F.col("w"))).alias("norm"))
        return v.join(norms, "id").select("id", "d", (F.col("w") / F.col("norm")).alias("w"))
    if how == "tfidf":
        n = v.select("id").distinct().agg(F.count("*").alias("n"))
        df = v.groupBy("d").agg(F.count("*").alias("df"))
        scored = v.join(df, "d").join(F.broadcast(n))  # one row
        return scored.select("id", "d", (F.col("w") * F.log(F.col("n") / F.col("df"))).alias("w")).where("w > 0")
    raise ValueError(how)


def synthetic_vectors(spark: SparkSession, n: int, dims: int = 10_000, nnz: int = 20, seed: int = 1) -> DataFrame:
    """The vectors of the ids below n."""
    return vectors_of_ids(spark.range(n), dims, nnz, seed)


def vectors_of_ids(ids: DataFrame, dims: int = 10_000, nnz: int = 20, seed: int = 1) -> DataFrame:
    """A vector for each id of ids (id) with about nnz features of weight 1-9 on hashed dimensions, each a function of its id."""
    rows = ids.select("id", F.explode(F.sequence(F.lit(1), F.lit(nnz))).alias("i"))
    spot = F.pmod(F.xxhash64("id", "i", F.lit(seed)), F.lit(dims)).alias("d")
    weight = (F.pmod(F.xxhash64("id", "i", F.lit(seed + 1)), F.lit(9)) + 1).alias("w")
    return rows.select("id", spot, weight).groupBy("id", "d").agg(F.max("w").alias("w"))
