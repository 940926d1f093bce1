"""Uses of the join: spectrum search, nearest-neighbour classification, spherical k-means."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import join_dot
from ..plans.api import knn_join
from ..sources.scratch import materialize
from .topk import top_k


def spectrum_search(queries: DataFrame, library: DataFrame, k: int = 5) -> DataFrame:
    """The k library spectra that match each measured spectrum best."""
    return knn_join(queries, library, k, method="inverted").withColumnsRenamed({"r_id": "query_id", "s_id": "library_id"})


def knn_classify(queries: DataFrame, train: DataFrame, labels: DataFrame, k: int = 5) -> DataFrame:
    """labels (id, label) -> r_id, predicted: the label with the most of k neighbours, then the larger score, then the smaller label."""
    near = knn_join(queries, train, k, method="inverted").join(labels.select(F.col("id").alias("s_id"), "label"), "s_id")
    votes = near.groupBy("r_id", "label").agg(F.count("*").alias("votes"), F.sum("score").alias("weight"))
    best = Window.partitionBy("r_id").orderBy(F.col("votes").desc(), F.col("weight").desc(), F.col("label"))
    return votes.withColumn("place", F.row_number().over(best)).where("place = 1").select("r_id", F.col("label").alias("predicted"), "votes")


def kmeans_assign(v: DataFrame, centroids: DataFrame) -> DataFrame:
    """id, centroid: the centroid with the largest dot product, the smaller id on ties; vectors that share nothing are left out."""
    return top_k(join_dot(v, centroids), 1).select(F.col("r_id").alias("id"), F.col("s_id").alias("centroid"), "score")


def kmeans_update(v: DataFrame, assigned: DataFrame) -> DataFrame:
    """Summed members as new centroids (id, d, w); in the spherical form only the direction counts."""
    return v.join(assigned.select("id", "centroid"), "id").groupBy(F.col("centroid").alias("id"), "d").agg(F.sum("w").alias("w"))


def kmeans_iterate(v: DataFrame, centroids: DataFrame, rounds: int = 3) -> DataFrame:
    """Assignment after some rounds, with centroids scaled to unit length in between; each round's centroids are written."""
    for _ in range(rounds - 1):
        updated = kmeans_update(v, kmeans_assign(v, centroids))
        norm = updated.groupBy("id").agg(F.sqrt(F.sum(F.col("w").cast("double") * F.col("w"))).alias("norm"))
        centroids = materialize(updated.join(norm, "id").select("id", "d", (F.col("w") / F.col("norm")).alias("w")), "centroids")
    return kmeans_assign(v, centroids)
