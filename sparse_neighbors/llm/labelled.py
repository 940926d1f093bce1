"""Bounded samples of labelled documents for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def remainder(doc_id: Column, mod: int) -> Column:
    """crc32 of the id as text, modulo mod; null for a null id."""
    return F.pmod(F.crc32(doc_id.cast("string")), F.lit(mod))


def sample_texts(docs: DataFrame, labels: DataFrame, column: str, mod: int, held: int, most: dict[int, int]) -> DataFrame:
    """(doc_id, text, label, weight) of at most most[label] labelled documents of each class outside the held-out part.

    The ids are drawn from the labels by hash, so they are few enough to go to every task and the texts are filtered
    where they are read. weight undoes the sampling of the classes. Repeated labels of a document count by majority;
    null labels and ids are ignored.
    """
    usable = labels.where(F.col("doc_id").isNotNull() & F.col(column).isNotNull() & (remainder(F.col("doc_id"), mod) != held))
    per_doc = usable.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg((F.avg(F.col(column).cast("double")) >= 0.5).cast("int").alias("label"))
    drawn = None
    for label, n in most.items():
        own = per_doc.where(F.col("label") == label)
        some = own.orderBy(F.xxhash64("doc_id", F.lit(11)), "doc_id").limit(n)
        total = own.count()
        some = some.withColumn("weight", F.lit(max(1.0, total / n)))
        drawn = some if drawn is None else drawn.unionByName(some)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.join(F.broadcast(drawn), "doc_id")
