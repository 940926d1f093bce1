"""Streaming queries; each ends with the batch result, which its SQL states."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from ..functions import vectors as V
from ..operators.inverted import candidate_scores
from ..sources.datasets import knn_sql, pair, table
from ..sources.scratch import new_path
from ..streaming import streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _events(s: SparkSession, d: str, parts: int = 3) -> DataFrame:
    return streams.stream_of(s, table(s, d, "events").select("event_id", "user_id", "ts", "event_type", "value"), parts)


query("st_tumbling", "select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by 1, 2")(
    lambda s, d: streams.collect_stream(_events(s, d).groupBy(F.window("ts", "1 hour")["start"].alias("start"), "event_type").agg(F.count("*").alias("n")))
)
query("st_sliding", "select time_bucket(interval 1 hour, ts) - to_hours(cast(i as int)) as start, count(*) as n from events, range(0, 3) t(i) group by 1")(
    lambda s, d: streams.collect_stream(_events(s, d).groupBy(F.window("ts", "3 hours", "1 hour")["start"].alias("start")).agg(F.count("*").alias("n")))
)
query("st_session", "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hour then 0 else 1 end as new from events), n as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as session from g) select user_id, min(ts) as start, count(*) as n from n group by user_id, session")(
    lambda s, d: streams.completed(_events(s, d).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))).select("user_id", F.col("w")["start"].alias("start"), "n")
)


@query("st_late", "select 0 as late_rows")
def st_late(s: SparkSession, d: str) -> DataFrame:
    """Rows older than the watermark after a newer file was read don't reach the windows they belong to."""
    e = table(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    path = new_path(s, "late")
    e.where("ts >= timestamp '2024-01-10'").coalesce(1).write.parquet(f"{path}/part=1")
    e.where("ts >= timestamp '2024-01-20'").coalesce(1).write.parquet(f"{path}/part=2")
    e.where("ts < timestamp '2024-01-05'").coalesce(1).write.parquet(f"{path}/part=3")
    stream = s.readStream.schema(e.schema.add("part", IntegerType())).option("maxFilesPerTrigger", 1).parquet(path)
    windows = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    out = streams.collect_stream(windows, "append")
    return out.where(F.col("window")["start"] < "2024-01-05").agg(F.count("*").cast("int").alias("late_rows"))


@query("st_dedup", "select user_id, count(*) as n from events group by 1")
def st_dedup(s: SparkSession, d: str) -> DataFrame:
    """Every event arrives twice and counts once."""
    e = table(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    stream = streams.stream_of(s, e.unionAll(e), 1)
    return streams.appended(stream.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])).groupBy("user_id").agg(F.count("*").alias("n"))


@query("st_stream_join", "select a.event_id as click_id, b.event_id as purchase_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")
def st_stream_join(s: SparkSession, d: str) -> DataFrame:
    e = _events(s, d, 1).withColumn("ts", F.col("ts").cast("timestamp"))
    a = e.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id")).withWatermark("click_ts", "2 hours")
    b = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id")).withWatermark("ts", "2 hours")
    joined = a.join(b, F.expr("u = user_id and ts >= click_ts and ts <= click_ts + interval 1 hour"))
    return streams.collect_stream(joined.select("click_id", "purchase_id"), "append")


@query("st_query_join", knn_sql("spectrum"))
def st_query_join(s: SparkSession, d: str) -> DataFrame:
    r, inner = pair(s, d, "spectrum")
    path = new_path(s, "query-join")
    streams.stream_query_join(streams.stream_of(s, V.pack(r), 3), inner, 5, path)
    return s.read.parquet(path).drop("batch")


@query("st_inner_join", knn_sql("spectrum"))
def st_inner_join(s: SparkSession, d: str) -> DataFrame:
    r, inner = pair(s, d, "spectrum")
    return streams.stream_inner_join(r, streams.stream_of(s, V.pack(inner), 3), 5, new_path(s, "inner-join"))


@query("st_topk_state", knn_sql("spectrum"))
def st_topk_state(s: SparkSession, d: str) -> DataFrame:
    """The newest output of each r is its result."""
    path = new_path(s, "topk-state")
    streams.stateful_topk(streams.stream_of(s, candidate_scores(*pair(s, d, "spectrum"), 5), 3), 5, path)
    rows = s.read.parquet(path)
    newest = rows.groupBy("r_id").agg(F.max("batch").alias("batch"))
    return rows.join(newest, ["r_id", "batch"]).select("r_id", "s_id", "score", "rank")


@query("st_rate_source", "select cast(v // 8 as bigint) as id, cast(v * 7919 % 50 as bigint) as d, cast(sum(1 + v % 5) as bigint) as w from range(0, 2000) t(v) group by 1, 2")
def st_rate_source(s: SparkSession, d: str) -> DataFrame:
    """The first 2000 features that the rate source makes, added up to vectors."""
    features = streams.first_values(streams.rate_features(s), 2000, new_path(s, "rate"))
    return features.groupBy("id", "d").agg(F.sum("w").alias("w"))
