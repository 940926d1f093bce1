"""The relational operators, functions, sources and sinks around the joins, one query per family."""

from __future__ import annotations

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..operators.inverted import read_index, write_index
from ..plans.api import knn_join
from ..sources.datasets import SQL, knn_sql, pair, table, vectors
from ..sources.scratch import new_path
from ..sources import svm_lines

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add



O, L, C, E = (lambda s, d, n=n: table(s, d, n) for n in ("orders", "lineitem", "customer", "events"))


# ---------------------------------------------------------------- projection, joins


@query("rel_project_filter", "select l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 2) as net, case when l_quantity >= 25 then 'large' else 'small' end as size from lineitem where l_quantity between 10 and 30 and l_returnflag in ('A', 'R') and l_linestatus like 'F%' and l_tax is not distinct from 0.02")
def rel_project_filter(s: SparkSession, d: str) -> DataFrame:
    kept = L(s, d).where(F.col("l_quantity").between(10, 30) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").like("F%") & F.col("l_tax").eqNullSafe(0.02))
    size = F.when(F.col("l_quantity") >= 25, "large").otherwise("small")
    return kept.select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 2).alias("net"), size.alias("size"))


for _how in ("inner", "left", "right", "full"):
    query(f"rel_join_{_how}", f"select c_custkey, o_orderkey from (select * from customer where c_mktsegment = 'BUILDING') c {_how} join (select * from orders where o_orderstatus = 'F') o on c_custkey = o_custkey")(
        lambda s, d, h=_how: C(s, d).where("c_mktsegment = 'BUILDING'").join(O(s, d).where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), h).select("c_custkey", "o_orderkey")
    )
BROADCAST_ROWS = 1 << 20  # of orders in one broadcast; more are joined by a shuffle, since the driver holds a broadcast whole


def _broadcast_hint(side: DataFrame, most: int = BROADCAST_ROWS) -> str:
    """Broadcast while the side is small, by all of its rows."""
    return "broadcast" if side.count() <= most else "shuffle_hash"


for _key, _hint in (("broadcast", _broadcast_hint), ("shuffle_hash", lambda side: "shuffle_hash"), ("merge", lambda side: "merge")):
    query(f"rel_join_{_key}", "select o_orderpriority, count(*) as n, cast(sum(l_quantity) as bigint) as quantity from orders join lineitem on o_orderkey = l_orderkey group by 1")(
        lambda s, d, h=_hint: _priorities(L(s, d), O(s, d).select("o_orderkey", "o_orderpriority"), h)
    )


def _priorities(lines: DataFrame, orders: DataFrame, hint) -> DataFrame:
    joined = lines.join(orders.hint(hint(orders)), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("bigint").alias("quantity"))


query("rel_semi", "select o_orderkey from orders where o_orderkey in (select l_orderkey from lineitem where l_quantity > 49)")(lambda s, d: O(s, d).join(L(s, d).where("l_quantity > 49"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey"))
query("rel_anti", "select c_custkey from customer where c_custkey not in (select o_custkey from orders)")(lambda s, d: C(s, d).join(O(s, d), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
_EXISTS = "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 400000)"
query("rel_exists", _EXISTS)(lambda s, d: s.sql(_EXISTS.replace("customer c", "{c} c").replace("orders o", "{o} o"), c=C(s, d), o=O(s, d)))
_SCALAR = "select o_orderkey from orders where o_totalprice > (select 1.5 * avg(o_totalprice) from orders)"
query("rel_scalar_subquery", _SCALAR)(lambda s, d: s.sql(_SCALAR.replace("from orders", "from {o}"), o=O(s, d)))
_LATERAL = "select c_custkey, o_orderkey from customer c, lateral (select o_orderkey from orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'F')"
query("rel_lateral", _LATERAL)(lambda s, d: s.sql(_LATERAL.replace("customer c", "{c} c").replace("orders o", "{o} o"), c=C(s, d), o=O(s, d)))
query("rel_cross_small", "select r_name, n_name from region, nation")(lambda s, d: table(s, d, "region").select("r_name").crossJoin(table(s, d, "nation").select("n_name")))
query("rel_theta", "select r.p_partkey as a, s.p_partkey as b from part r join part s on r.p_size = s.p_size and r.p_retailprice > s.p_retailprice + 500")(
    lambda s, d: _theta(table(s, d, "part"))
)


def _theta(part: DataFrame) -> DataFrame:
    """Per size only prices with a partner on the other side are paired: above the lowest by more than 500, and below the highest likewise.

    Every row that is left has a row of the result at least; a size without a pair costs two scans.
    """
    a, b = (part.select(F.col("p_partkey").alias(n), F.col("p_size").alias(f"size_{n}"), F.col("p_retailprice").alias(f"price_{n}")) for n in "ab")
    ends = part.where("p_retailprice is not null").groupBy("p_size").agg(F.min("p_retailprice").alias("low"), F.max("p_retailprice").alias("high")).where("high > low + 500")
    above = a.join(ends, F.col("size_a") == F.col("p_size")).where("price_a > low + 500").select("a", "size_a", "price_a")
    below = b.join(ends, F.col("size_b") == F.col("p_size")).where("high > price_b + 500").select("b", "size_b", "price_b")
    return above.join(below, (F.col("size_a") == F.col("size_b")) & (F.col("price_a") > F.col("price_b") + 500)).select("a", "b")


@query("rel_range", "select e.event_id, p.p_partkey from events e join part p on p.p_retailprice >= e.value * 10 and p.p_retailprice < e.value * 10 + 1 where e.event_type = 'purchase'")
def rel_range(s: SparkSession, d: str) -> DataFrame:
    """A range join by buckets as wide as the range: two equi-joined buckets instead of all pairs."""
    e = E(s, d).where("event_type = 'purchase'").select("event_id", (F.col("value") * 10).alias("low"))
    e = e.select("event_id", "low", F.explode(F.array(F.floor("low"), F.floor("low") + 1)).alias("bucket"))
    p = table(s, d, "part").select("p_partkey", "p_retailprice", F.floor("p_retailprice").alias("bucket"))
    return e.join(p, "bucket").where("p_retailprice >= low and p_retailprice < low + 1").select("event_id", "p_partkey")


_HOUR = "a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts < a.ts + interval 1 day"
query("rel_interval", f"select a.event_id as click_id, b.event_id as purchase_id from events a join events b on {_HOUR}")(lambda s, d: _interval(E(s, d)))


def _interval(e: DataFrame) -> DataFrame:
    a = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("click_ts"), F.col("event_id").alias("click_id"))
    b = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"))
    return a.join(b, "user_id").where("ts >= click_ts and ts < click_ts + interval 1 day").select("click_id", "purchase_id")


@query("rel_asof", "select p.event_id, max(c.ts) as last_click from events p left join events c on c.user_id = p.user_id and c.event_type = 'click' and c.ts <= p.ts where p.event_type = 'purchase' group by 1")
def rel_asof(s: SparkSession, d: str) -> DataFrame:
    """The newest click at or before each purchase: one sorted pass per user instead of a join."""
    e = E(s, d).where("event_type in ('click', 'purchase')")
    so_far = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    click = F.when(F.col("event_type") == "click", F.col("ts"))
    return e.withColumn("last_click", F.max(click).over(so_far)).where("event_type = 'purchase'").select("event_id", "last_click")


query("rel_self_pairs", f"with v as ({SQL['supplier_part']}) select r.id as r_id, s.id as s_id, cast(sum(r.w * s.w) as bigint) as score from v r join v s on r.d = s.d and s.id > r.id group by 1, 2")(lambda s, d: _self_pairs(vectors(s, d, "supplier_part")))


def _self_pairs(v: DataFrame) -> DataFrame:
    r, s = v.select(F.col("id").alias("r_id"), "d", F.col("w").alias("rw")), v.select(F.col("id").alias("s_id"), "d", F.col("w").alias("sw"))
    return r.join(s, "d").where("s_id > r_id").groupBy("r_id", "s_id").agg(F.sum(F.col("rw") * F.col("sw")).alias("score"))


# ---------------------------------------------------------------- aggregates

query("rel_agg_hash", "select l_returnflag, l_linestatus, cast(sum(l_quantity) as bigint) as quantity, count(*) as n, max(l_shipdate) as last, min(l_partkey) as least from lineitem group by 1, 2")(
    lambda s, d: L(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("bigint").alias("quantity"), F.count("*").alias("n"), F.max("l_shipdate").alias("last"), F.min("l_partkey").alias("least"))
)
query("rel_agg_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")(lambda s, d: L(s, d).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
_FILTERED = "select l_returnflag, count(*) filter (where l_quantity > 25) as large, cast(sum(l_quantity) filter (where l_discount > 0.05) as bigint) as discounted from lineitem group by 1"
query("rel_agg_filtered", _FILTERED)(lambda s, d: s.sql(_FILTERED.replace("lineitem", "{l}"), l=L(s, d)))
query("rel_agg_stats", "select l_returnflag, round(stddev_samp(l_quantity), 6) as deviation, round(var_pop(l_quantity), 6) as variance, round(quantile_cont(l_quantity, 0.5), 6) as median from lineitem group by 1")(
    lambda s, d: L(s, d).groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("deviation"), F.round(F.var_pop("l_quantity"), 6).alias("variance"), F.round(F.percentile("l_quantity", 0.5), 6).alias("median"))
)
query("rel_agg_approx")(lambda s, d: L(s, d).agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.countDistinct("l_partkey") - 1) < 0.1).alias("distinct_ok"), (F.abs(F.percentile_approx("l_quantity", 0.5) - F.percentile("l_quantity", 0.5)) <= 1).alias("median_ok"), (F.abs(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")) / F.countDistinct("l_partkey") - 1) < 0.1).alias("sketch_ok")))
query("rel_agg_max_by", "select o_custkey, arg_max(o_orderkey, o_totalprice) as dearest, arg_min(o_orderkey, o_totalprice) as cheapest from orders group by 1")(lambda s, d: _dearest(O(s, d)))


def _dearest(orders: DataFrame) -> DataFrame:
    """Of orders that tie in price, the one of lowest key, which is the first in the table; null keys and prices count for nothing."""
    key, price = F.col("o_orderkey"), F.col("o_totalprice")
    known = key.isNotNull() & price.isNotNull()
    dear, cheap = (F.when(known, F.struct(price.alias("price"), k.alias("key"))) for k in (-key, key))
    return orders.groupBy("o_custkey").agg((-F.max(dear)["key"]).alias("dearest"), F.min(cheap)["key"].alias("cheapest"))


for _kind in ("rollup", "cube"):
    query(f"rel_{_kind}", f"select o_orderstatus, o_orderpriority, count(*) as n from orders group by {_kind}(o_orderstatus, o_orderpriority)")(lambda s, d, k=_kind: getattr(O(s, d), k)("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")))
_SETS = "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())"
query("rel_grouping_sets", _SETS)(lambda s, d: s.sql(_SETS.replace("from orders", "from {o}"), o=O(s, d)))
query("rel_pivot", "select o_orderpriority, count(*) filter (where o_orderstatus = 'F') as F, count(*) filter (where o_orderstatus = 'O') as O, count(*) filter (where o_orderstatus = 'P') as P from orders group by 1")(
    lambda s, d: O(s, d).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)
)
query("rel_unpivot", "select c_custkey, 'nation' as what, cast(c_nationkey as bigint) as value from customer union all select c_custkey, 'balance', cast(floor(c_acctbal) as bigint) from customer")(
    lambda s, d: C(s, d).select("c_custkey", F.col("c_nationkey").cast("bigint").alias("nation"), F.floor("c_acctbal").alias("balance")).unpivot("c_custkey", ["nation", "balance"], "what", "value")
)

# ---------------------------------------------------------------- windows



def _by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")



query("rel_win_rank", "select o_orderkey, cast(row_number() over w as int) as n, cast(rank() over v as int) as r, cast(dense_rank() over v as int) as dr, round(percent_rank() over v, 6) as pr, round(cume_dist() over v, 6) as cd from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey), v as (partition by o_custkey order by o_orderstatus)")(lambda s, d: _ranks(O(s, d)))


def _ranks(o: DataFrame) -> DataFrame:
    w, v = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    return o.select("o_orderkey", F.row_number().over(w).alias("n"), F.rank().over(v).alias("r"), F.dense_rank().over(v).alias("dr"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


query("rel_win_frame_rows", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 4) as recent, first_value(event_id) over (partition by user_id order by ts, event_id) as first_id, nth_value(event_id, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second_id from events")(
    lambda s, d: E(s, d).select("event_id", F.round(F.sum("value").over(_by_user().rowsBetween(-2, 0)), 4).alias("recent"), F.first("event_id").over(_by_user()).alias("first_id"), F.nth_value("event_id", 2).over(_by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second_id"))
)
query("rel_win_frame_range", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as in_day from events")(
    lambda s, d: E(s, d).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)).alias("in_day"))
)
query("rel_win_lag_lead", "select event_id, lag(event_type) over w as before, lead(event_type, 2, 'none') over w as after from events window w as (partition by user_id order by ts, event_id)")(lambda s, d: E(s, d).select("event_id", F.lag("event_type").over(_by_user()).alias("before"), F.lead("event_type", 2, "none").over(_by_user()).alias("after")))
query("rel_win_ntile", "select o_orderkey, cast(ntile(4) over (partition by o_orderpriority order by o_totalprice, o_orderkey) as int) as quarter from orders")(lambda s, d: O(s, d).select("o_orderkey", F.ntile(4).over(Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")).alias("quarter")))

# ---------------------------------------------------------------- order, sets, samples

query("rel_sort_limit", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 100")(lambda s, d: O(s, d).select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100))
query("rel_topk_global", "select c_custkey, c_acctbal from customer order by c_acctbal desc, c_custkey limit 10")(lambda s, d: C(s, d).select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey").limit(10))
query("rel_offset", "select o_orderkey from orders order by o_totalprice, o_orderkey limit 50 offset 25")(lambda s, d: O(s, d).orderBy("o_totalprice", "o_orderkey").select("o_orderkey").offset(25).limit(50))
query("rel_topk_per_key", "select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as n from orders) where n <= 3")(
    lambda s, d: O(s, d).withColumn("n", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("n <= 3").select("o_custkey", "o_orderkey")
)
for _name, _op, _call in (("union", "union all", "union"), ("intersect", "intersect", "intersect"), ("intersect_all", "intersect all", "intersectAll"), ("except", "except", "subtract"), ("except_all", "except all", "exceptAll")):
    query(f"rel_{_name}", f"select l_partkey as k from lineitem where l_quantity > 20 {_op} select l_partkey from lineitem where l_discount > 0.05")(
        lambda s, d, c=_call: getattr(L(s, d).where("l_quantity > 20").select(F.col("l_partkey").alias("k")), c)(L(s, d).where("l_discount > 0.05").select("l_partkey"))
    )
query("rel_union_by_name", "select c_custkey as k, c_name as name from customer union all select s_suppkey, s_name from supplier")(lambda s, d: C(s, d).select(F.col("c_custkey").alias("k"), F.col("c_name").alias("name")).unionByName(table(s, d, "supplier").select(F.col("s_name").alias("name"), F.col("s_suppkey").alias("k"))))
query("rel_sample_hash", "select doc_id from documents where doc_id % 7 = 3")(lambda s, d: table(s, d, "documents").where("doc_id % 7 = 3").select("doc_id"))
query("rel_sample_stratified")(lambda s, d: O(s, d).sampleBy("o_orderstatus", {"F": 0.2, "O": 0.1, "P": 0.5}, seed=5).groupBy("o_orderstatus").agg(F.count("*").alias("n")))

# ---------------------------------------------------------------- scalar functions

query("fn_string", r"select p_partkey, upper(p_name) as u, length(p_name) as n, substring(p_name, 2, 4) as part, regexp_replace(p_brand, '[0-9]+', '#') as brand, concat_ws('-', p_brand, p_type) as joined, trim('  x ') as t, translate(p_brand, 'BD', 'bd') as tr, levenshtein(p_brand, p_type) as lev, split(p_name, ' ')[1] as first_word from part")(
    lambda s, d: table(s, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.length("p_name").alias("n"), F.substring("p_name", 2, 4).alias("part"), F.regexp_replace("p_brand", "[0-9]+", "#").alias("brand"), F.concat_ws("-", "p_brand", "p_type").alias("joined"), F.trim(F.lit("  x ")).alias("t"), F.translate("p_brand", "BD", "bd").alias("tr"), F.levenshtein("p_brand", "p_type").alias("lev"), F.split("p_name", " ")[0].alias("first_word"))
)
query("fn_date", "select event_id, date_trunc('hour', ts) as h, cast(dayofweek(ts) + 1 as int) as dow, date_diff('day', timestamp '2024-01-01', ts) as days, epoch_us(ts) as us, ts + interval 90 minute as later, time_bucket(interval 15 minute, ts) as quarter from events")(
    lambda s, d: E(s, d).select("event_id", F.date_trunc("hour", "ts").alias("h"), F.dayofweek("ts").alias("dow"), F.datediff("ts", F.lit("2024-01-01")).cast("bigint").alias("days"), F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), (F.col("ts") + F.make_interval(mins=F.lit(90))).alias("later"), F.window("ts", "15 minutes")["start"].alias("quarter"))
)
query("fn_math", "select event_id, cast(floor(value) as bigint) as f, round(ln(1 + value), 6) as l, round(sqrt(value), 6) as q, floor(pow(value, 2)) as p, abs(value - 100) as a, greatest(value, 100.0) as g, least(value, 100.0) as le, cast(event_id % 7 as bigint) as m, case when event_id % 5 = 0 then null else round(value / (event_id % 5), 6) end as safe from events")(
    lambda s, d: E(s, d).select("event_id", F.floor("value").alias("f"), F.round(F.log1p("value"), 6).alias("l"), F.round(F.sqrt("value"), 6).alias("q"), F.floor(F.pow("value", F.lit(2))).cast("double").alias("p"), F.abs(F.col("value") - 100).alias("a"), F.greatest("value", F.lit(100.0)).alias("g"), F.least("value", F.lit(100.0)).alias("le"), F.pmod("event_id", F.lit(7)).alias("m"), F.round(F.try_divide("value", F.col("event_id") % 5), 6).alias("safe"))
)
_ARR = "with a as (select l_orderkey, list_sort(list(l_partkey)) as p from lineitem group by 1)"
query("fn_array", f"{_ARR} select l_orderkey, len(p) as n, p[1] as first_p, cast(list_sum(list_transform(p, lambda x: x * 2)) as bigint) as doubled, len(list_filter(p, lambda x: x % 2 = 0)) as even, len(list_distinct(p)) as different from a")(
    lambda s, d: L(s, d).groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_partkey")).alias("p")).select("l_orderkey", F.size("p").cast("bigint").alias("n"), F.col("p")[0].alias("first_p"), F.aggregate(F.transform("p", lambda x: x * 2), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("doubled"), F.size(F.filter("p", lambda x: x % 2 == 0)).cast("bigint").alias("even"), F.size(F.array_distinct("p")).cast("bigint").alias("different"))
)
query("fn_map", f"with v as ({SQL['supplier_part']}) select id, count(*) as n, cast(sum(case when w > 50 then 1 else 0 end) as bigint) as heavy, cast(max(w) as bigint) as top from v group by id")(
    lambda s, d: V.as_map(V.pack(vectors(s, d, "supplier_part"))).select("id", F.size(F.map_keys("features")).cast("bigint").alias("n"), F.size(F.map_filter("features", lambda k, x: x > 50)).cast("bigint").alias("heavy"), F.array_max(F.map_values("features")).alias("top"))
)
query("fn_json", "select event_id, cast(props ->> '$.k' as int) as k, case when cast(props ->> '$.k' as int) > 50 then 'high' else 'low' end as band from events")(
    lambda s, d: E(s, d).select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.when(F.variant_get(F.parse_json("props"), "$.k", "int") > 50, "high").otherwise("low").alias("band"))
)

# ---------------------------------------------------------------- user-defined surface


@query("udf_sql_dot", f"with v as ({SQL['supplier_part']}) select id, cast(sum(w * w) as bigint) as norm from v group by id")
def udf_sql_dot(s: SparkSession, d: str) -> DataFrame:
    s.sql("create or replace temporary function weight_square_sum(f array<struct<d: bigint, w: bigint>>) returns bigint return aggregate(f, 0l, (a, x) -> a + x.w * x.w)")
    V.pack(vectors(s, d, "supplier_part")).createOrReplaceTempView("packed_suppliers")
    return s.sql("select id, weight_square_sum(features) as norm from packed_suppliers")


@query("udaf_kth", "with k as (" + knn_sql("supplier_self") + ") select r_id, score as kth from k where rank = 5")
def udaf_kth(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("bigint")
    def fifth(scores: pd.Series) -> int:
        return int(scores.nlargest(5).iloc[-1])

    return knn_join(*pair(s, d, "supplier_self"), method="inverted").groupBy("r_id").agg(fifth("score").alias("kth"))


@query("udtf_matches", knn_sql("spectrum", 1).replace("cast(rank as int) as rank", "1 as rank"))
def udtf_matches(s: SparkSession, d: str) -> DataFrame:
    @F.udtf(returnType="r_id bigint, s_id bigint, score bigint, rank int")
    class TopMatches:
        """Keeps the best row of each partition of its table argument."""

        def __init__(self):
            self.best = None

        def eval(self, row):
            if self.best is None or (-row["score"], row["s_id"]) < (-self.best["score"], self.best["s_id"]):
                self.best = row

        def terminate(self):
            if self.best is not None:
                yield self.best["r_id"], self.best["s_id"], self.best["score"], 1

    from ..functions.similarity import join_dot

    return TopMatches(join_dot(*pair(s, d, "spectrum")).asTable().partitionBy("r_id"))


# ---------------------------------------------------------------- sources and sinks

_LONG = "id bigint, d bigint, w bigint"
for _format in ("parquet", "json", "csv", "orc"):

    def _round_trip(s, d, f=_format):
        path = new_path(s, f"round-trip-{f}")
        vectors(s, d, "supplier_part").write.format(f).save(path)
        return s.read.format(f).schema(_LONG).load(path)

    query(f"io_roundtrip_{_format}", SQL["supplier_part"])(_round_trip)


@query("io_bucketed", knn_sql("supplier_self"))
def io_bucketed(s: SparkSession, d: str) -> DataFrame:
    """Both sides bucketed by d once, so the join on d shuffles neither."""
    name = "bucketed_supplier_vectors"
    s.sql(f"drop table if exists {name}")
    vectors(s, d, "supplier_part").write.bucketBy(8, "d").sortBy("d").mode("overwrite").option("path", new_path(s, "bucketed")).saveAsTable(name)
    v = s.table(name)
    return knn_join(v, v, method="inverted")


@query("io_index", knn_sql("supplier_self"))
def io_index(s: SparkSession, d: str) -> DataFrame:
    """Posting lists written once and read back for the join."""
    path = new_path(s, "index")
    v = vectors(s, d, "supplier_part")
    write_index(v, path, 4)
    return knn_join(v, read_index(s, path).select(F.col("s_id").alias("id"), "d", "w"), method="inverted")


@query("io_partitioned", "select o_orderstatus, o_orderkey from orders where o_orderstatus = 'F'")
def io_partitioned(s: SparkSession, d: str) -> DataFrame:
    path = new_path(s, "partitioned")
    O(s, d).select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'")


@query("io_svm_lines", SQL["supplier_part"])
def io_svm_lines(s: SparkSession, d: str) -> DataFrame:
    """Lines `id d:w d:w` written as text and read through a Python data source."""
    path = new_path(s, "svm")
    svm_lines.write_lines(vectors(s, d, "supplier_part"), path)
    cloudpickle.register_pickle_by_value(svm_lines)  # its planner process needn't find this package
    s.dataSource.register(svm_lines.SvmLines)
    return s.read.format("svm_lines").load(path)
