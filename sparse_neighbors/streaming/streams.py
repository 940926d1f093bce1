"""Streams: R arriving against a fixed S, S arriving block by block against a fixed R, bounded top-k state, event windows."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..functions import vectors as V
from ..operators.exhaustive import cell_scores
from ..operators.inverted import accumulate, cells, inverted_join
from ..operators.pruned import block_dimstats, pruned_block
from ..operators.resident import RESIDENT_BYTES, feature_bytes
from ..plans.nested_loop import keep_best, merge_candidates, thresholds
from ..sources.scratch import discard, materialize, new_path


PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_to_end(writer, provider: str = "") -> None:
    """Process what is there, then stop. provider: of the state, where it isn't the session's."""
    spark = SparkSession.getActiveSession()
    before = spark.conf.get(PROVIDER)
    if provider:
        spark.conf.set(PROVIDER, provider)
    try:
        query = writer.trigger(availableNow=True).start()
    finally:
        if provider:
            spark.conf.set(PROVIDER, before)
    query.awaitTermination()
    if query.exception():
        raise query.exception()


def stream_of(spark: SparkSession, batch: DataFrame, parts: int = 3, by: str | None = None) -> DataFrame:
    """A file stream of a batch frame, one file a trigger."""
    path = new_path(spark, "stream")
    (batch.repartition(parts, by) if by else batch.repartition(parts)).write.parquet(path)
    return spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1).parquet(path)


def stream_query_join(r_stream: DataFrame, s: DataFrame, k: int, path: str) -> None:
    """Each micro-batch of packed R vectors meets all of S; a batch's folder is overwritten if it is replayed."""

    def one(batch: DataFrame, number: int) -> None:
        inverted_join(V.unpack(batch), s, k).write.mode("overwrite").parquet(f"{path}/batch={number}")

    run_to_end(r_stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{path}-progress"))


def stream_inner_join(r: DataFrame, s_stream: DataFrame, k: int, path: str) -> DataFrame:
    """Each micro-batch of packed S vectors is an S-block; state n is made from state n - 1, so a replay changes nothing.

    The k-th scores of a state are the floors of the next batch, of which only what can reach them is indexed. Batches come in any
    order of ids, so ties with a floor are kept.
    """
    spark, kind = r.sparkSession, r.schema["w"].dataType.simpleString()
    left = materialize(r.select(F.lit(0).alias("rb"), F.col("id").alias("r_id"), "d", "w"), "outer")
    dimstats = materialize(block_dimstats(left), "dimstats")
    packed = materialize(left.groupBy("rb", "r_id").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("features")), "packed")
    resident = feature_bytes(left) <= RESIDENT_BYTES
    last = []

    def one(batch: DataFrame, number: int) -> None:
        block = V.unpack(batch).withColumnRenamed("id", "s_id")
        grid = cells(left.withColumnRenamed("r_id", "id"), block.withColumnRenamed("s_id", "id"))
        if number:
            old = spark.read.parquet(f"{path}/state={number - 1}")
            kth = thresholds(old)
            new = pruned_block(left, block, kth, dimstats, r_packed=packed, resident=resident, grid=grid, k=k)
            after = merge_candidates(old, new, kth, k, strict=False)
        else:
            whole = cell_scores(left.withColumnRenamed("r_id", "id"), block.withColumnRenamed("s_id", "id"), k, *grid).withColumn("rb", F.lit(0)) if grid else None
            new = accumulate(left, block, by=("rb",)) if whole is None else whole
            after = keep_best(new.where("score > 0"), k)
        after.write.mode("overwrite").parquet(f"{path}/state={number}")
        if number:
            discard(new._written)
        last[:] = [number]

    run_to_end(s_stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{path}-progress"))
    discard(left, dimstats, packed)
    columns = ("r_id", "s_id", "score", "rank")
    return spark.read.parquet(f"{path}/state={last[0]}").select(*columns) if last else spark.createDataFrame([], f"r_id long, s_id long, score {kind}, rank int")


def rate_features(spark: SparkSession, rate: int = 1000, per_vector: int = 8, dims: int = 50) -> DataFrame:
    """A stream of generated features from the rate source: value, id, d, w."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rate).option("numPartitions", 2).load()
    value = F.col("value")
    return rows.select("value", F.floor(value / per_vector).alias("id"), (value * 7919 % dims).alias("d"), (1 + value % 5).alias("w"))


def first_values(stream: DataFrame, n: int, path: str) -> DataFrame:
    """The rows of the first n values of an endless stream: it runs until a batch has passed them, then stops."""
    passed = []

    def one(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        top = batch.sparkSession.read.parquet(f"{path}/batch={number}").agg(F.max("value")).first()[0]
        if top is not None and top >= n - 1:
            passed.append(number)

    query = stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{path}-progress").start()
    try:
        while not passed and query.isActive:
            query.awaitTermination(0.2)
    finally:
        query.stop()
    if query.exception():
        raise query.exception()
    return stream.sparkSession.read.parquet(path).where(F.col("value") < n).drop("batch")


def stateful_topk(scores_stream: DataFrame, k: int, path: str) -> None:
    """scores (r_id, s_id, score) -> the current k best per r after every batch; state is k rows per r."""

    def keep(key, batches, state):
        rows = [tuple(x) for x in zip(*state.get, strict=True)] if state.exists else []
        for pdf in batches:
            rows += list(zip(pdf["s_id"].tolist(), pdf["score"].tolist(), strict=True))
            rows = sorted(rows, key=lambda x: (-x[1], x[0]))[:k]
        state.update(([x[0] for x in rows], [x[1] for x in rows]))
        yield pd.DataFrame({"r_id": key[0], "s_id": [x[0] for x in rows], "score": [x[1] for x in rows], "rank": range(1, len(rows) + 1)})

    def one(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/batch={number}")

    out = scores_stream.groupBy("r_id").applyInPandasWithState(keep, "r_id long, s_id long, score long, rank int", "ids array<long>, scores array<long>", "update", GroupStateTimeout.NoTimeout)
    run_to_end(out.writeStream.outputMode("update").foreachBatch(one).option("checkpointLocation", f"{path}-progress"))


def collect_stream(df: DataFrame, mode: str = "complete") -> DataFrame:
    """The final table of a stream through the memory sink."""
    name = f"stream_{uuid.uuid4().hex}"
    run_to_end(df.writeStream.outputMode(mode).format("memory").queryName(name))
    return df.sparkSession.table(name)


def completed(df: DataFrame) -> DataFrame:
    """The final table of a stream in complete mode, a folder a batch, with its state on disk: the last one is the result, and the driver holds no rows."""
    spark, path, last = df.sparkSession, new_path(df.sparkSession, "completed"), []

    def one(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last[:] = [number]

    run_to_end(df.writeStream.outputMode("complete").foreachBatch(one).option("checkpointLocation", f"{path}-progress"), ROCKSDB)
    return spark.read.schema(df.schema).parquet(f"{path}/batch={last[0]}") if last else spark.createDataFrame([], df.schema)


def appended(df: DataFrame) -> DataFrame:
    """All rows of a stream in append mode through Parquet, with its state on disk: neither the driver nor an executor's heap holds them."""
    path = new_path(df.sparkSession, "appended")
    run_to_end(df.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", f"{path}-progress"), ROCKSDB)
    return df.sparkSession.read.schema(df.schema).parquet(path)
