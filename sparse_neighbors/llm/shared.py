"""Shared folder, materialised intermediates and worker set-up for the operators of this subpackage."""

from __future__ import annotations

import ctypes
import gc
import os
import uuid
from contextlib import contextmanager
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = str(Path(__file__).resolve().parents[2])
BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"


def prepare_workers(spark: SparkSession) -> None:
    """Let Python workers import this package when it isn't installed on their path."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *paths])


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, from `spark.checkpoint.dir`.

    Where the session names none, a local folder is set, which is right only for a local master;
    on a cluster that is an error rather than a silent loss of files.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = known.get() if known.isDefined() else None
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = f"file:///tmp/checkpoints/{spark.sparkContext.applicationId}"
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._materialized_at = path
    return back


def discard(*frames: DataFrame) -> None:
    """Delete materialised frames that nothing will read again."""
    for df in frames:
        path = getattr(df, "_materialized_at", None)
        if path:
            spark = df.sparkSession
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
    if frames:
        collect_garbage(frames[0].sparkSession)


def collect_garbage(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished jobs, which it does when the driver drops what refers to them."""
    give_back()
    spark._jvm.System.gc()


def give_back() -> None:
    """Return this process's unused memory to the system; else allocators keep what they once held."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def release_heap(spark: SparkSession) -> None:
    """Let executors' JVMs collect, upon which they return heap that they don't use; what an earlier step grew isn't there for Python workers otherwise."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.expr("reflect('java.lang.System', 'gc')")).collect()


def giving_back(run):
    """A function on batches whose worker, which waits for further tasks beside the JVM, gives its unused memory back at its end."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


@contextmanager
def short_batches(spark: SparkSession, rows: int):
    """Jobs started inside send Arrow batches of at most `rows` rows, which JVM and worker hold at once for every task; the session's own limit is back afterwards."""
    own = spark.conf.get(BATCH_ROWS)
    if not 0 < int(own) <= rows:
        spark.conf.set(BATCH_ROWS, str(rows))
    try:
        yield
    finally:
        spark.conf.set(BATCH_ROWS, own)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
