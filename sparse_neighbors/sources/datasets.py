"""Vector sets on the given tables, and the same sets as SQL for the oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as V

TYPE_CODES = {"purchase": 0, "view": 1, "signup": 2, "error": 3, "click": 4}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")


def _bought(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return _lines(spark, sf_dir).join(orders, "l_orderkey")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    code = F.create_map(*(F.lit(x) for kv in TYPE_CODES.items() for x in kv))[F.col("event_type")]
    k = F.get_json_object("props", "$.k").cast("bigint")
    return table(spark, sf_dir, "events").select("user_id", "ts", "event_type", "value", k.alias("k"), (F.col("user_id") * 10 + code).alias("user_type"), (F.col("user_id") * 100 + F.dayofmonth("ts")).alias("user_day"))


def vectors(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the named vector sets in long form with whole weights."""
    t = lambda n: table(spark, sf_dir, n)
    make = {
        "customer_part": lambda: V.from_long(_bought(spark, sf_dir), "o_custkey", "l_partkey", "l_quantity"),
        "part_customer": lambda: V.from_long(_bought(spark, sf_dir), "l_partkey", "o_custkey", "l_quantity"),
        "supplier_part": lambda: V.from_long(_lines(spark, sf_dir), "l_suppkey", "l_partkey", "l_quantity"),
        "order_part": lambda: V.from_long(_lines(spark, sf_dir), "l_orderkey", "l_partkey", "l_quantity"),
        "user_type_spectrum": lambda: V.from_peaks(_events(spark, sf_dir), "user_type", "value", "k"),
        "user_spectrum": lambda: V.from_peaks(_events(spark, sf_dir), "user_id", "value", "k"),
        "user_day_spectrum": lambda: V.from_peaks(_events(spark, sf_dir), "user_day", "value", "k"),
        "document_terms": lambda: V.from_text(t("documents"), "doc_id", "text"),
        "benchmark_terms": lambda: V.from_text(t("benchmark"), "item_id", "text"),
        "page_terms": lambda: V.from_text(t("pages"), "page_id", "html"),
        "conversation_terms": lambda: V.from_text(t("conversations"), "conv_id", "text"),
        "embedding_positive": lambda: V.from_dense(t("embeddings"), "vec_id", "embedding"),
    }[name]()
    return V.counted(make)


def _sql_long(source: str, id: str, d: str, w: str) -> str:
    return f"select * from (select {id} as id, {d} as d, cast(sum({w}) as bigint) as w from {source} group by 1, 2) where w > 0"


def _sql_text(source: str, id: str, text: str) -> str:
    split = rf"select {id} as id, unnest(regexp_split_to_array(lower({text}), '[ \n\t\r]+')) as d from {source}"
    return f"select id, d, cast(count(*) as bigint) as w from ({split}) where d <> '' group by 1, 2"


_BOUGHT = "lineitem join orders on l_orderkey = o_orderkey"
_CODE = "case event_type " + " ".join(f"when '{k}' then {v}" for k, v in TYPE_CODES.items()) + " end"
_BIN, _K = "cast(floor(value * 10) as bigint)", "cast(props ->> '$.k' as bigint)"
SQL = {
    "customer_part": _sql_long(_BOUGHT, "o_custkey", "l_partkey", "l_quantity"),
    "part_customer": _sql_long(_BOUGHT, "l_partkey", "o_custkey", "l_quantity"),
    "supplier_part": _sql_long("lineitem", "l_suppkey", "l_partkey", "l_quantity"),
    "order_part": _sql_long("lineitem", "l_orderkey", "l_partkey", "l_quantity"),
    "user_type_spectrum": _sql_long("events", f"user_id * 10 + {_CODE}", _BIN, _K),
    "user_spectrum": _sql_long("events", "user_id", _BIN, _K),
    "user_day_spectrum": _sql_long("events", "user_id * 100 + day(ts)", _BIN, _K),
    "document_terms": _sql_text("documents", "doc_id", "text"),
    "benchmark_terms": _sql_text("benchmark", "item_id", "text"),
    "page_terms": _sql_text("pages", "page_id", "html"),
    "conversation_terms": _sql_text("conversations", "conv_id", "text"),
    "embedding_positive": "select id, d, w from (select vec_id as id, cast(i as bigint) as d, cast(round(cast(embedding[i + 1] as double) * 1000) as bigint) as w from embeddings, range(0, 64) t(i)) where w > 0",
}

#: R and S of the experiments: vector set and condition on id.
PAIRS = {
    "benchmark_doc": (("benchmark_terms", "true"), ("document_terms", "true")),
    "spectrum": (("user_type_spectrum", "id % 10 = 0"), ("user_type_spectrum", "id % 10 <> 0")),
    "order": (("order_part", "id % 2 = 0"), ("order_part", "id % 2 = 1")),
    "customer": (("customer_part", "id % 2 = 0"), ("customer_part", "id % 2 = 1")),
    "supplier_customer": (("supplier_part", "true"), ("customer_part", "true")),
    "customer_order": (("customer_part", "true"), ("order_part", "true")),
    "doc": (("document_terms", "id % 10 = 0"), ("document_terms", "id % 10 <> 0")),
    "page": (("page_terms", "id % 2 = 0"), ("page_terms", "id % 2 = 1")),
    "conversation": (("conversation_terms", "id % 2 = 0"), ("conversation_terms", "id % 2 = 1")),
    "embedding": (("embedding_positive", "id % 2 = 0"), ("embedding_positive", "id % 2 = 1")),
    "supplier_self": (("supplier_part", "true"), ("supplier_part", "true")),
}


def pair(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    return tuple(vectors(spark, sf_dir, v).where(c) for v, c in PAIRS[name])


def pair_sql(name: str) -> str:
    """`rv` and `sv` as common table expressions."""
    (r, rc), (s, sc) = PAIRS[name]
    return f"rv as materialized (select * from ({SQL[r]}) where {rc}), sv as materialized (select * from ({SQL[s]}) where {sc})"


def scores_sql(name: str, extra: str = "") -> str:
    return f"with {pair_sql(name)}, scores as (select rv.id as r_id, sv.id as s_id, cast(sum(rv.w * sv.w) as bigint) as score from rv join sv on rv.d = sv.d {extra} group by 1, 2)"


def knn_sql(name: str, k: int = 5, ties: str = "id", extra: str = "") -> str:
    """The exact result of every method on a pair."""
    head = scores_sql(name, extra)
    if ties == "id":
        ranked = "select *, row_number() over (partition by r_id order by score desc, s_id) as rank from scores"
        return f"{head} select r_id, s_id, score, cast(rank as int) as rank from ({ranked}) where rank <= {k}"
    ranked = "select *, rank() over (partition by r_id order by score desc) as rank, count(*) over (partition by r_id, score) as same from scores"
    where = f"rank <= {k}" if ties == "all" else f"rank + same - 1 <= {k}"
    return f"{head} select r_id, s_id, score, cast(rank as int) as rank from ({ranked}) where {where}"
