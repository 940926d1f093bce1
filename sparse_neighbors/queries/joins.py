"""Queries of vectors, joins, intermediates, costs, workloads and applications, each with its SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import similarity
from ..functions import vectors as V
from ..operators import apps, costs, inverted, resident
from ..operators.exhaustive import exhaustive_grid, exhaustive_join
from ..operators.inverted import every_score, inverted_join, inverted_packed, posting_lists
from ..operators.pair_cells import met_pairs
from ..operators.pruned import PruneOptions, block_dimstats, block_floors, live_vectors, pruned_block, split_features
from ..operators.resident import resident_join
from ..operators.topk import from_best, kth_scores, merge_best, to_best, to_nested
from ..plans.api import explain_join, knn_join
from ..plans.blocks import BlockPlan, assign_blocks, plan_blocks, plan_sizes
from ..plans.nested_loop import block_join, join_report
from ..sources.datasets import SQL, knn_sql, pair, pair_sql, scores_sql, table, vectors
from ..sources.scratch import discard, materialize

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def blocks(r: int, s: int) -> BlockPlan:
    return BlockPlan(0, 0, r, s)


# ---------------------------------------------------------------- vectors and statistics

for _name, _sql in SQL.items():
    query(f"vec_{_name}", _sql)(lambda spark, d, n=_name: vectors(spark, d, n))

_V1 = f"with v as ({SQL['customer_part']})"
query("vec_packed", f"{_V1} select id, cast(count(*) as int) as n, cast(sum(w) as bigint) as total, min(d) as first_d, max(d) as last_d from v group by id")(
    lambda s, d: V.pack(vectors(s, d, "customer_part")).select("id", F.size("features").alias("n"), F.aggregate("features", F.lit(0).cast("bigint"), lambda a, x: a + x["w"]).alias("total"), F.col("features")[0]["d"].alias("first_d"), F.element_at("features", -1)["d"].alias("last_d"))
)
query("vec_map_form", f"{_V1} select id, cast(count(*) as int) as n, cast(sum(w) as bigint) as total from v group by id")(
    lambda s, d: V.as_map(V.pack(vectors(s, d, "customer_part"))).select("id", F.size("features").alias("n"), F.aggregate(F.map_values("features"), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"))
)
query("vec_round_trip", SQL["customer_part"])(lambda s, d: V.unpack(V.pack(vectors(s, d, "customer_part"))))
query("vec_dictionary", f"with v as ({SQL['benchmark_terms']}) select d, row_number() over (order by d) - 1 as number from (select distinct d from v)")(lambda s, d: V.dimension_dictionary(vectors(s, d, "benchmark_terms")))
query("vec_l2", f"{_V1} select id, d, round(w / sqrt(sum(w * w) over (partition by id)), 6) as w from v")(lambda s, d: V.reweight(vectors(s, d, "customer_part"), "l2").withColumn("w", F.round("w", 6)))
query("vec_tfidf", f"with v as ({SQL['benchmark_terms']}), n as (select count(distinct id) as n from v), f as (select d, count(*) as df from v group by d) select id, v.d, round(w * ln(n / df), 6) as w from v join f on v.d = f.d, n where w * ln(n / df) > 0")(
    lambda s, d: V.reweight(vectors(s, d, "benchmark_terms"), "tfidf").withColumn("w", F.round("w", 6))
)
query("vec_validated", SQL["customer_part"])(lambda s, d: V.validate_vectors(vectors(s, d, "customer_part")))
query("vec_synthetic", "select cast(count(distinct c_custkey) as int) as n_vectors, true as in_range from customer")(
    lambda s, d: V.vectors_of_ids(table(s, d, "customer").select(F.col("c_custkey").alias("id")), 1000, 20, 3).agg(F.countDistinct("id").cast("int").alias("n_vectors"), F.every((F.col("d") >= 0) & (F.col("d") < 1000) & F.col("w").between(1, 9)).alias("in_range"))
)
query("stat_vector_sizes", f"{_V1} select id, count(*) as n_features, cast(sum(w) as bigint) as total_weight, max(w) as max_weight from v group by id")(lambda s, d: V.vector_sizes(vectors(s, d, "customer_part")))
query("stat_dim_frequency", f"{_V1} select d, count(*) as freq from v group by d")(lambda s, d: V.dimension_stats(vectors(s, d, "customer_part")).select("d", "freq"))
query("stat_dim_peak", f"{_V1} select d, max(w) as peak_weight from v group by d")(lambda s, d: V.dimension_stats(vectors(s, d, "customer_part")).select("d", "peak_weight"))
query("stat_sparsity_summary", f"{_V1} select count(distinct id) as n_vectors, count(distinct d) as n_dims, count(*) as n_features from v")(lambda s, d: V.sparsity(vectors(s, d, "customer_part")))


def _blocked(spark, sf_dir, name, nr, ns):
    r, s = pair(spark, sf_dir, name)
    return assign_blocks(r, nr, "mod", "rb"), assign_blocks(s, ns, "mod", "sb")


_RANKED = "select rb, d, count(*) as freq, max(w) as peak_weight, cast(row_number() over (partition by rb order by count(*) desc, d) as int) as dim_rank from r2 group by rb, d"
_R2 = "r2 as (select *, cast(id % 2 as int) as rb from rv), s3 as (select *, cast(id % 3 as int) as sb from sv)"
query("stat_block_dim_rank", f"with {pair_sql('supplier_customer')}, {_R2} {_RANKED}")(lambda s, d: block_dimstats(_blocked(s, d, "supplier_customer", 2, 3)[0]))

# ---------------------------------------------------------------- exhaustive

query("knn_exhaustive_benchmark_doc", knn_sql("benchmark_doc"))(lambda s, d: exhaustive_join(*pair(s, d, "benchmark_doc")))
query("knn_exhaustive_spectrum", knn_sql("spectrum"))(lambda s, d: exhaustive_join(*pair(s, d, "spectrum")))
query("knn_exhaustive_customer", knn_sql("customer"))(lambda s, d: exhaustive_grid(*pair(s, d, "customer"), r_blocks=1, s_blocks=8))
query("knn_exhaustive_blocked", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum"), kernel="exhaustive", plan=blocks(1, 3)))
query("knn_exhaustive_grid", knn_sql("customer"))(lambda s, d: exhaustive_grid(*pair(s, d, "customer"), r_blocks=2, s_blocks=3))

# ---------------------------------------------------------------- inverted

for _pair in ("customer", "supplier_customer", "customer_order", "order", "spectrum", "benchmark_doc", "doc", "page", "conversation", "embedding"):
    query(f"knn_inverted_{_pair}", knn_sql(_pair))(lambda s, d, p=_pair: inverted_join(*pair(s, d, p)))
query("knn_inverted_blocked", knn_sql("customer"))(lambda s, d: block_join(*pair(s, d, "customer"), kernel="inverted", plan=blocks(2, 3)))
query("knn_inverted_packed", knn_sql("customer"))(lambda s, d: inverted_packed(*pair(s, d, "customer"), heavy=20))
query("posting_lists", f"with v as ({SQL['customer_part']}) select d, count(*) as n, cast(sum(w) as bigint) as total from v group by d")(
    lambda s, d: posting_lists(vectors(s, d, "customer_part"), packed=True).select("d", F.size("postings").cast("bigint").alias("n"), F.aggregate("postings", F.lit(0).cast("bigint"), lambda a, x: a + x["w"]).alias("total"))
)

# ---------------------------------------------------------------- pruned

_STRICT = PruneOptions(rule="strict")
for _pair in ("customer", "supplier_customer", "order", "spectrum", "benchmark_doc", "doc"):
    query(f"knn_pruned_{_pair}", knn_sql(_pair))(lambda s, d, p=_pair: block_join(*pair(s, d, p), kernel="pruned", plan=blocks(2, 3)))
query("knn_pruned_strict", knn_sql("benchmark_doc"))(lambda s, d: block_join(*pair(s, d, "benchmark_doc"), plan=blocks(2, 4), options=_STRICT))
query("knn_pruned_rare_first", knn_sql("benchmark_doc"))(lambda s, d: block_join(*pair(s, d, "benchmark_doc"), plan=blocks(2, 3), options=PruneOptions(dim_order="rare_first")))
query("knn_pruned_natural_order", knn_sql("benchmark_doc"))(lambda s, d: block_join(*pair(s, d, "benchmark_doc"), plan=blocks(2, 3), options=PruneOptions(dim_order="natural")))
query("knn_pruned_keep_dead", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum"), plan=blocks(2, 3), options=PruneOptions(drop_dead=False)))
query("knn_pruned_precheck", knn_sql("benchmark_doc"))(lambda s, d: block_join(*pair(s, d, "benchmark_doc"), plan=blocks(2, 3), options=PruneOptions(precheck=True)))
query("knn_pruned_seeded", knn_sql("benchmark_doc"))(lambda s, d: block_join(*pair(s, d, "benchmark_doc"), plan=blocks(2, 3), s_how="geometric"))
query("knn_pruned_any_order", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum"), plan=blocks(2, 3), s_how="hash", order=[2, 0, 1]))
query("knn_pruned_one_block", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum"), plan=blocks(1, 1)))
query("knn_pruned_default_plan", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum")))

# ---------------------------------------------------------------- ties and options

query("knn_ties_all", knn_sql("spectrum", ties="all"))(lambda s, d: knn_join(*pair(s, d, "spectrum"), method="inverted", ties="all"))
query("knn_ties_strict", knn_sql("spectrum", ties="strict"))(lambda s, d: knn_join(*pair(s, d, "spectrum"), method="inverted", ties="strict"))
query("knn_pruned_ties_all", knn_sql("spectrum", ties="all"))(lambda s, d: knn_join(*pair(s, d, "spectrum"), method="pruned", ties="all", plan=blocks(2, 3)))
query("knn_pruned_ties_strict", knn_sql("spectrum", ties="strict"))(lambda s, d: knn_join(*pair(s, d, "spectrum"), method="pruned", ties="strict", plan=blocks(2, 3)))
query("knn_exclude_self", knn_sql("supplier_self", extra="where rv.id <> sv.id"))(lambda s, d: knn_join(*pair(s, d, "supplier_self"), method="inverted", exclude_self=True))
query("knn_k1", knn_sql("customer", 1))(lambda s, d: inverted_join(*pair(s, d, "customer"), k=1))
query("knn_k20", knn_sql("benchmark_doc", 20))(lambda s, d: inverted_join(*pair(s, d, "benchmark_doc"), k=20))
query("knn_auto", knn_sql("benchmark_doc"))(lambda s, d: knn_join(*pair(s, d, "benchmark_doc")))
query(
    "knn_fill_zero",
    f"with {pair_sql('spectrum')}, scores as (select rv.id as r_id, sv.id as s_id, cast(sum(rv.w * sv.w) as bigint) as score from rv join sv on rv.d = sv.d group by 1, 2), pairs as (select r.id as r_id, s.id as s_id from (select distinct id from rv) r, (select distinct id from sv) s), filled as (select p.r_id, p.s_id, coalesce(score, 0) as score from pairs p left join scores c on p.r_id = c.r_id and p.s_id = c.s_id) select r_id, s_id, score, cast(rank as int) as rank from (select *, row_number() over (partition by r_id order by score desc, s_id) as rank from filled) where rank <= 5",
)(lambda s, d: knn_join(*pair(s, d, "spectrum"), method="inverted", fill_zero=True))
query("knn_nested_result", f"with k as ({knn_sql('benchmark_doc')}) select r_id, cast(count(*) as int) as n, min(case when rank = 1 then s_id end) as best, cast(sum(score) as bigint) as total from k group by r_id")(
    lambda s, d: to_nested(inverted_join(*pair(s, d, "benchmark_doc"))).select("r_id", F.size("neighbours").alias("n"), F.col("neighbours")[0]["s_id"].alias("best"), F.aggregate("neighbours", F.lit(0).cast("bigint"), lambda a, x: a + x["score"]).alias("total"))
)
query("knn_cosine", f"with {pair_sql('benchmark_doc')}, rn as (select id, sqrt(sum(w * w)) as n from rv group by id), sn as (select id, sqrt(sum(w * w)) as n from sv group by id), scores as (select rv.id as r_id, sv.id as s_id, sum(rv.w * sv.w) as dot from rv join sv on rv.d = sv.d group by 1, 2), c as (select r_id, s_id, dot / (rn.n * sn.n) as cosine from scores join rn on r_id = rn.id join sn on s_id = sn.id) select r_id, round(max(cosine), 6) as best from c group by r_id")(
    lambda s, d: knn_join(*pair(s, d, "benchmark_doc"), k=1, method="inverted", metric="cosine").select("r_id", F.round("score", 6).alias("best"))
)

# ---------------------------------------------------------------- S in place, blocks of R broadcast

for _pair in ("spectrum", "benchmark_doc"):
    query(f"knn_resident_{_pair}", knn_sql(_pair))(lambda s, d, p=_pair: resident_join(*pair(s, d, p)))
query("knn_resident_blocks", knn_sql("customer"))(lambda s, d: resident_join(*pair(s, d, "customer"), block_bytes=1 << 18))
query("knn_resident_ties_all", knn_sql("spectrum", ties="all"))(lambda s, d: knn_join(*pair(s, d, "spectrum"), ties="all", strategy="resident"))
query("knn_resident_exclude_self", knn_sql("supplier_self", extra="where rv.id <> sv.id"))(lambda s, d: knn_join(*pair(s, d, "supplier_self"), method="inverted", strategy="resident", exclude_self=True))


@query("topk_array_merge", knn_sql("spectrum"))
def topk_array_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The results of the two halves of S as arrays, merged per r."""
    r, s = pair(spark, sf_dir, "spectrum")
    s = assign_blocks(s, 2, "range", "half")
    a, b = (to_best(inverted_join(r, s.where(F.col("half") == n).drop("half"))) for n in (0, 1))
    both = a.join(b.withColumnRenamed("best", "other"), "r_id", "full")
    return from_best(both.select("r_id", merge_best(F.col("best"), F.col("other"), 5).alias("best")))


# ---------------------------------------------------------------- intermediates of the pruned join, after the first of three S-blocks

_FIRST_STATE = f"with {pair_sql('spectrum')}, {_R2}, scores as (select r2.rb, r2.id as r_id, s3.id as s_id, cast(sum(r2.w * s3.w) as bigint) as score from r2 join s3 on r2.d = s3.d where sb = 0 group by 1, 2, 3), ranked as (select *, row_number() over (partition by r_id order by score desc, s_id) as rank from scores), ids as (select distinct rb, id as r_id from r2), kth as (select ids.rb, ids.r_id, coalesce(score, 0) as kth_score from ids left join ranked on ids.r_id = ranked.r_id and rank = 2)"
_LIVE = "live as (select distinct r2.rb, r2.id as r_id from r2 join s3 on r2.d = s3.d where sb = 1), floors as (select kth.rb, min(kth_score) as block_floor from kth join live on kth.r_id = live.r_id group by kth.rb)"
_SPLIT = f"stats as ({_RANKED}), walked as (select rb, s3.id as s_id, s3.d, s3.w, cast(sum(peak_weight * s3.w) over (partition by rb, s3.id order by dim_rank, s3.d rows unbounded preceding) as bigint) as bound from s3 join stats on s3.d = stats.d where sb = 1), split as (select walked.*, bound >= block_floor and bound > 0 as is_tail from walked join floors on walked.rb = floors.rb)"


def _state(spark, sf_dir):
    r, s = _blocked(spark, sf_dir, "spectrum", 2, 3)
    outer = r.select("rb", F.col("id").alias("r_id"), "d", "w")
    inner = s.select("sb", F.col("id").alias("s_id"), "d", "w")
    ids = outer.select("rb", "r_id").distinct()
    near = inverted_join(r.select("id", "d", "w"), s.where("sb = 0").select("id", "d", "w"), 2).drop("rank")
    kth = kth_scores(near.join(ids, "r_id"), ids, 2)
    return outer, inner.where("sb = 1").drop("sb"), kth


def _split(spark, sf_dir):
    outer, block, kth = _state(spark, sf_dir)
    return outer, split_features(block, block_dimstats(outer), block_floors(kth, live_vectors(outer, block)))


query("kth_scores", f"{_FIRST_STATE} select * from kth")(lambda s, d: _state(s, d)[2].withColumn("kth_score", F.col("kth_score").cast("bigint")))
query("block_floor_after_first", f"{_FIRST_STATE}, {_LIVE} select * from floors")(lambda s, d: block_floors(_state(s, d)[2], live_vectors(*_state(s, d)[:2])).withColumn("block_floor", F.col("block_floor").cast("bigint")))
query("feature_split", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT} select rb, s_id, d, w, bound, is_tail from split")(lambda s, d: _split(s, d)[1].withColumn("bound", F.col("bound").cast("bigint")))
query("tail_posting_lengths", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT} select rb, d, count(*) as n from split where is_tail group by rb, d")(lambda s, d: _split(s, d)[1].where("is_tail").groupBy("rb", "d").agg(F.count("*").alias("n")))
query("head_bounds", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT} select rb, s_id, max(bound) as head_bound from split where not is_tail group by rb, s_id")(lambda s, d: _split(s, d)[1].where("not is_tail").groupBy("rb", "s_id").agg(F.max("bound").cast("bigint").alias("head_bound")))


@query("pruned_candidates", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT}, met as (select distinct r2.rb, r2.id as r_id, s_id from split join r2 on split.rb = r2.rb and split.d = r2.d where is_tail) select met.rb, met.r_id, met.s_id, cast(sum(r2.w * s3.w) as bigint) as score from met join r2 on met.r_id = r2.id join s3 on met.s_id = s3.id and r2.d = s3.d group by 1, 2, 3")
def pruned_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    outer, block, kth = _state(spark, sf_dir)
    grid = inverted.cells(outer.withColumnRenamed("r_id", "id"), block.withColumnRenamed("s_id", "id"))
    return pruned_block(outer, block, kth, block_dimstats(outer), PruneOptions(precheck=False), grid=grid and inverted.for_tasks(outer, grid), every=True)


# ---------------------------------------------------------------- costs

_COST = f"with {pair_sql('supplier_customer')}, n as (select (select count(distinct id) from rv) as n_r, (select count(*) from rv) as r_features, (select count(distinct id) from sv) as n_s, (select count(*) from sv) as s_features, (select cast(sum(fr * fs) as bigint) from (select d, count(*) as fr from rv group by d) a join (select d, count(*) as fs from sv group by d) b on a.d = b.d) as products)"
_P = "supplier_customer"
query("cost_c1_sample", f"with {pair_sql('benchmark_doc')}, a as (select id, count(*) as n from rv group by id), b as (select id, count(*) as n from sv group by id) select a.id as r_id, b.id as s_id, a.n + b.n as steps from a, b")(lambda s, d: costs.cost_pair(*pair(s, d, "benchmark_doc")))
query("cost_c2", f"{_COST} select n_s * r_features + n_r * s_features as c2 from n")(lambda s, d: costs.cost_exhaustive(*pair(s, d, _P)))
query("cost_c3", f"{_COST} select s_features, products, s_features + products as c3 from n")(lambda s, d: costs.cost_inverted(*pair(s, d, _P)))
query("cost_ratio", f"{_COST} select round((n_s * r_features + n_r * s_features) / (s_features + products), 6) as ratio from n")(lambda s, d: costs.summary(*pair(s, d, _P)).select(F.round(F.expr(costs.C2) / F.expr(costs.C3), 6).alias("ratio")))
_BCOST = f"with {pair_sql(_P)}, {_R2}, a as (select rb, count(distinct id) as n_r, count(*) as r_features from r2 group by rb), b as (select sb, count(distinct id) as n_s, count(*) as s_features from s3 group by sb)"
query("cost_c2_blocked", f"{_BCOST} select rb, sb, n_s * r_features + n_r * s_features as c2 from a, b")(lambda s, d: costs.cost_exhaustive_blocked(*_blocked(s, d, _P, 2, 3)))
query("cost_c3_blocked", f"{_BCOST}, p as (select rb, sb, cast(sum(fr * fs) as bigint) as products from (select rb, d, count(*) as fr from r2 group by rb, d) x join (select sb, d, count(*) as fs from s3 group by sb, d) y on x.d = y.d group by rb, sb) select p.rb, p.sb, s_features, products, s_features + products as c3 from p join b on p.sb = b.sb")(
    lambda s, d: costs.cost_inverted_blocked(*_blocked(s, d, _P, 2, 3))
)
query("cost_pruned", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT}, fr as (select rb, d, count(*) as fr from r2 group by rb, d) select split.rb, count(*) as indexed_features, cast(sum(fr) as bigint) as scanned_postings from split join fr on split.rb = fr.rb and split.d = fr.d where is_tail group by split.rb")(lambda s, d: costs.cost_pruned(*_split(s, d)))
_MET = "met as (select distinct r2.rb, r2.id as r_id, s_id from split join r2 on split.rb = r2.rb and split.d = r2.d where is_tail), sizes as (select id as r_id, count(*) as nr from r2 group by id), heads as (select rb, s_id, count(*) as nh from split where not is_tail group by rb, s_id)"
query("cost_completion", f"{_FIRST_STATE}, {_LIVE}, {_SPLIT}, {_MET} select met.rb, count(*) as candidates, cast(sum(case when nh is null then 0 else nr + nh end) as bigint) as completion_steps from met join sizes on met.r_id = sizes.r_id left join heads on met.rb = heads.rb and met.s_id = heads.s_id group by met.rb")(lambda s, d: costs.cost_completion(*_split(s, d)))


def _plan_sql(name: str, fraction: float, layout: str = "split") -> str:
    return f"""with {pair_sql(name)}, p as (select greatest(1, cast(ceil((select count(*) from rv) * 12 / 8192.0) as int)) as rp, greatest(1, cast(ceil((select count(*) from sv) * 12 / 8192.0) as int)) as sp),
      b as (select *, greatest(2, cast(ceil((rp + sp) * {fraction}::double) as int)) as buffer from p), c as (select *, greatest(1, cast(floor(buffer * 0.8::double) as int)) as rb from b), e as (select *, greatest(1, buffer - rb) as sb from c)
      select rp as r_pages, sp as s_pages, cast(ceil(rp / rb::double) as int) as r_blocks, cast(ceil(sp / sb::double) as int) as s_blocks from e"""


def _classic_sql(name: str, fraction: float) -> str:
    """A page for S and one for output; all else holds R."""
    return f"""with {pair_sql(name)}, p as (select greatest(1, cast(ceil((select count(*) from rv) * 12 / 8192.0) as int)) as rp, greatest(1, cast(ceil((select count(*) from sv) * 12 / 8192.0) as int)) as sp),
      b as (select *, greatest(1, greatest(2, cast(ceil((rp + sp) * {fraction}::double) as int)) - 2) as buffer from p)
      select rp as r_pages, sp as s_pages, cast(ceil(rp / buffer::double) as int) as r_blocks, sp as s_blocks, cast(rp + ceil(rp / buffer::double) * sp as int) as io_pages from b"""


def _classic_row(spark, sf_dir, fraction: float) -> DataFrame:
    plan = plan_blocks(*pair(spark, sf_dir, _P), buffer_fraction=fraction, layout="classic")
    return _plan_row(spark, plan, io_pages=plan.io_pages)


def _plan_row(spark, plan: BlockPlan, **more) -> DataFrame:
    values = {"r_pages": plan.r_pages, "s_pages": plan.s_pages, "r_blocks": plan.r_blocks, "s_blocks": plan.s_blocks} | more
    return spark.range(1).select(*(F.lit(v).alias(k) for k, v in values.items()))


query("block_plan", _plan_sql(_P, 0.5))(lambda s, d: _plan_row(s, plan_blocks(*pair(s, d, _P))))
query("block_plan_classic", _classic_sql(_P, 0.3))(lambda s, d: _classic_row(s, d, 0.3))
query("io_pages", f"select cast(r_pages + r_blocks * s_pages as int) as io_pages from ({_plan_sql(_P, 0.5)})")(lambda s, d: s.range(1).select(F.lit(plan_blocks(*pair(s, d, _P)).io_pages).alias("io_pages")))
query("block_assignment", f"with {pair_sql(_P)}, sizes as (select id, count(*) as size from sv group by id), placed as (select id, coalesce(sum(size) over (order by id rows between unbounded preceding and 1 preceding), 0) / (sum(size) over ())::double as share from sizes) select id, cast(least(floor(share * 4), 3) as int) as block from placed")(
    lambda s, d: assign_blocks(pair(s, d, _P)[1], 4).select("id", "block").distinct()
)
query("explain_join", f"{_COST} select 'inverted' as method, n_s * r_features + n_r * s_features as c2, s_features + products as c3, products * 24 as shuffle_bytes from n")(lambda s, d: explain_join(*pair(s, d, _P)).select("method", "c2", "c3", "shuffle_bytes"))

# ---------------------------------------------------------------- theorem


def _missed(spark, sf_dir, name="spectrum"):
    r, s = pair(spark, sf_dir, name)
    exact = inverted_join(r, s)
    pruned = block_join(r, s, plan=blocks(2, 3))
    return exact.exceptAll(pruned).select(F.lit("missed").alias("kind")).unionAll(pruned.exceptAll(exact).select(F.lit("added").alias("kind")))


query("theorem_missed_pairs", "select 0 as missed")(lambda s, d: _missed(s, d).agg(F.count("*").cast("int").alias("missed")))


@query("methods_agree", "select true as agree")
def methods_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, s = pair(spark, sf_dir, "spectrum")
    results = [exhaustive_join(r, s), inverted_join(r, s), inverted_packed(r, s), exhaustive_grid(r, s), block_join(r, s, plan=blocks(2, 3))]
    every = results[0]
    for x in results[1:]:
        every = every.unionByName(x)
    rows = every.groupBy("r_id", "s_id", "score", "rank").agg(F.count("*").alias("n"))
    return rows.agg(F.every(F.col("n") == len(results)).alias("agree"))


# ---------------------------------------------------------------- experiment workloads


def _first_ids(v: DataFrame, n: int) -> DataFrame:
    """Vectors of the n lowest ids: the data size is the parameter of these experiments. Only the n-th id reaches the driver."""
    last = v.select("id").distinct().orderBy("id").limit(n).agg(F.max("id")).first()[0]
    return v.where(F.lit(False) if last is None else F.col("id") <= last)


def _steps(spark, sf_dir):
    """A fifth of the vectors of the smaller side, as the unit of the size sweep."""
    r, s = pair(spark, sf_dir, "order")
    return r, s, max(1, min(r.select("id").distinct().count(), s.select("id").distinct().count()) // 5)


_W1 = f"with {pair_sql('order')}, unit as (select greatest(1, least((select count(distinct id) from rv), (select count(distinct id) from sv)) // 5) as u), ro as (select *, dense_rank() over (order by id) as place from rv), so as (select *, dense_rank() over (order by id) as place from sv), steps as (select unnest([1, 2, 3, 4, 5]) as step), scores as (select step, ro.id as r_id, so.id as s_id, cast(sum(ro.w * so.w) as bigint) as score from ro join so on ro.d = so.d, steps, unit where ro.place <= step * u and so.place <= step * u group by 1, 2, 3), ranked as (select *, row_number() over (partition by step, r_id order by score desc, s_id) as rank from scores) select cast(step as int) as step, count(*) as n, cast(sum(score) as bigint) as total, cast(max(score) as bigint) as best from ranked where rank <= 5 group by step"


def _digest(result: DataFrame, **parameters) -> DataFrame:
    return result.agg(*(F.any_value(F.lit(v)).alias(k) for k, v in parameters.items()), F.count("*").alias("n"), F.sum("score").alias("total"), F.max("score").alias("best"))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for x in frames[1:]:
        out = out.unionByName(x)
    return out


@query("w1_size_sweep", _W1)
def w1_size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Data size in five steps, equal sizes."""
    r, s, unit = _steps(spark, sf_dir)
    return _union([_digest(inverted_join(_first_ids(r, unit * i), _first_ids(s, unit * i)), step=i) for i in range(1, 6)])


RATIOS = (1, 2, 5, 10, 20, 50, 100)
_W2 = f"with v as materialized ({SQL['order_part']}), o as (select *, dense_rank() over (order by id) as place from v), unit as (select greatest(1, count(distinct id) // 110) as u from v), steps as (select unnest([1, 2, 5, 10, 20, 50, 100]) as ratio), scores as (select ratio, r.id as r_id, s.id as s_id, cast(sum(r.w * s.w) as bigint) as score from o r join o s on r.d = s.d, steps, unit where r.place <= 10 * u and s.place > 10 * u and s.place <= (10 + ratio) * u group by 1, 2, 3), ranked as (select *, row_number() over (partition by ratio, r_id order by score desc, s_id) as rank from scores) select cast(ratio as int) as ratio, count(*) as n, cast(sum(score) as bigint) as total, cast(max(score) as bigint) as best from ranked where rank <= 5 group by ratio"


@query("w2_ratio_sweep", _W2)
def w2_ratio_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """R fixed, S from a tenth of its size to ten times it."""
    v = vectors(spark, sf_dir, "order_part")
    unit = max(1, v.select("id").distinct().count() // 110)
    r = _first_ids(v, 10 * unit)
    return _union([_digest(inverted_join(r, _first_ids(v, (10 + x) * unit).join(r.select("id").distinct(), "id", "left_anti")), ratio=x) for x in RATIOS])


def _k_sweep_sql(name: str) -> str:
    return f"{scores_sql(name)}, ranked as (select *, row_number() over (partition by r_id order by score desc, s_id) as rank from scores), ks as (select unnest([5, 10, 15, 20]) as k) select cast(k as int) as k, count(*) as n, cast(sum(score) as bigint) as total, cast(max(score) as bigint) as best from ranked, ks where rank <= k group by k"


for _pair in ("spectrum", "benchmark_doc"):
    query(f"w3_k_sweep{'' if _pair == 'spectrum' else '_' + _pair}", _k_sweep_sql(_pair))(lambda s, d, p=_pair: _union([_digest(inverted_join(*pair(s, d, p), k=k), k=k) for k in (5, 10, 15, 20)]))

FRACTIONS = (0.5, 0.4, 0.3, 0.2, 0.1)
query("w4_buffer_sweep", " union all ".join(f"select {f}::double as fraction, *, r_pages + r_blocks * s_pages as io_pages from ({_plan_sql('spectrum', f)})" for f in FRACTIONS))(
    lambda s, d: _buffer_sweep(s, d)
)


def _buffer_sweep(spark, sf_dir):
    """Blocks and pages as the buffer shrinks; the join's result doesn't change."""
    r, s = (v.count() for v in pair(spark, sf_dir, "spectrum"))
    plans = [(f, plan_sizes(r, s, f)) for f in FRACTIONS]
    return _union([_plan_row(spark, p, fraction=f, io_pages=p.io_pages) for f, p in plans])


query("w4_result_at_small_buffer", knn_sql("spectrum"))(lambda s, d: block_join(*pair(s, d, "spectrum"), plan=blocks(3, 5)))

# ---------------------------------------------------------------- the three methods side by side, with the work of each


def _blocks_sql(v: str, n: str, column: str) -> str:
    """v plus its range block; n is a number or a scalar subquery."""
    sizes = f"select id, count(*) as size from {v} group by id"
    share = "coalesce(sum(size) over (order by id rows between unbounded preceding and 1 preceding), 0) / (sum(size) over ())::double"
    return f"select {v}.*, {column} from {v} join (select id, cast(least(floor({share} * {n}), {n} - 1) as int) as {column} from ({sizes})) using (id)"


def _work_sql(nr: int, ns: int, k: int) -> str:
    """CTEs from `rv` and `sv` to `report`: the state before S-block n is the exact result over the blocks before it."""
    return f"""rblock as materialized ({_blocks_sql("rv", str(nr), "rb")}), sblock as materialized ({_blocks_sql("sv", str(ns), "sb")}),
      pairs as materialized (select rb, rblock.id as r_id, sb, sblock.id as s_id, cast(sum(rblock.w * sblock.w) as bigint) as score from rblock join sblock on rblock.d = sblock.d group by 1, 2, 3, 4),
      turns as (select unnest(range(1, {ns})) as n), placed as (select n, r_id, score, row_number() over (partition by n, r_id order by score desc, s_id) as rank from pairs, turns where sb < n),
      kths as materialized (select i.rb, i.r_id, n, coalesce(score, 0) as kth_score from (select distinct rb, id as r_id from rblock) i cross join turns left join (select n, r_id, score from placed where rank = {k}) using (n, r_id)),
      floor as (select n as sb, kths.rb, min(kth_score) as block_floor from kths join (select distinct sb as n, r_id from pairs) using (n, r_id) group by 1, 2),
      stats as (select rb, d, count(*) as freq, max(w) as peak_weight, row_number() over (partition by rb order by count(*) desc, d) as dim_rank from rblock group by rb, d),
      walk as (select sb, rb, sblock.id as s_id, d, w, freq, cast(sum(peak_weight * w) over (partition by rb, sblock.id order by dim_rank, d rows unbounded preceding) as bigint) as bound from sblock join stats using (d) where sb > 0),
      cut as materialized (select *, bound >= block_floor and bound > 0 as is_tail from walk join floor using (sb, rb)),
      visit as (select sb, rb, count(*) as indexed, cast(sum(freq) as bigint) as scanned from cut where is_tail group by 1, 2),
      rsize as (select id as r_id, count(*) as nr from rblock group by id), head as (select rb, s_id, count(*) as nh, max(bound) as head_bound from cut where not is_tail group by 1, 2),
      met as (select sb, cut.rb, rblock.id as r_id, s_id, cast(sum(rblock.w * cut.w) as bigint) as score from cut join rblock on cut.rb = rblock.rb and cut.d = rblock.d where is_tail group by 1, 2, 3, 4),
      tried as (select met.sb, met.rb, nr + nh as steps, (score + head_bound) * (1 + 1e-9::double) >= kth_score as reach from met join rsize using (r_id) join kths on kths.n = met.sb and kths.r_id = met.r_id left join head on head.rb = met.rb and head.s_id = met.s_id),
      done as (select sb, rb, count(*) as candidates, count(*) filter (reach) as completed, cast(coalesce(sum(steps) filter (reach), 0) as bigint) as completion_steps from tried group by 1, 2),
      report as (select sb, rb, cast(block_floor as bigint) as block_floor, coalesce(indexed, 0) as indexed, coalesce(scanned, 0) as scanned, coalesce(candidates, 0) as candidates, coalesce(completed, 0) as completed, coalesce(completion_steps, 0) as completion_steps from floor left join visit using (sb, rb) left join done using (sb, rb)
        union all select 0, rb, 0, (select count(*) from sblock where sb = 0), coalesce((select cast(sum(a.fr * b.fs) as bigint) from (select d, count(*) as fr from rblock x where x.rb = q.rb group by d) a join (select d, count(*) as fs from sblock where sb = 0 group by d) b on a.d = b.d), 0), (select count(*) from pairs p where p.sb = 0 and p.rb = q.rb), 0, 0 from (select distinct rb from rblock) q)"""


query("join_report", f"with {pair_sql('spectrum')}, {_work_sql(2, 3, 5)} select cast(sb as int) as sb, rb, block_floor, indexed, scanned, candidates, completed, completion_steps from report")(lambda s, d: join_report(*pair(s, d, "spectrum"), plan=blocks(2, 3)))

METHODS = ("exhaustive", "inverted", "pruned")


def _three(r: DataFrame, s: DataFrame, best: int, plan: BlockPlan, **point) -> DataFrame:
    """Digest and work of each method at one point: pairs merged (exhaustive), postings built and visited (inverted), both and completion steps (pruned).

    Lists are built anew for every R-block, by both indexed methods.
    """
    r, s = materialize(r, "side"), materialize(s, "side")
    work: list[DataFrame] = []
    found = [exhaustive_join(r, s, best), inverted_join(r, s, best), block_join(r, s, best, "pruned", plan, work=work)]
    counted = costs.summary(r, s)
    steps = [counted.select(F.expr(costs.C2).alias("work")), counted.select(F.expr(f"{plan.r_blocks} * s_features + products").alias("work"))]
    steps.append(_union(work).agg(F.sum(F.expr("indexed + scanned + completion_steps")).alias("work")))
    out = materialize(_union([_digest(f, **point, method=m).crossJoin(w) for f, w, m in zip(found, steps, METHODS, strict=True)]), "point")
    discard(r, s, *work)
    return out


def _three_sql(sides: str, nr: int, ns: int, near: int, **point) -> str:
    """One point: `sides` gives the CTEs rv and sv."""
    values = "".join(f"cast({v} as {'double' if isinstance(v, float) else 'int'}) as {c}, " for c, v in point.items())
    n = "(select count(distinct id) from {0}v) * (select count(*) from {1}v)".format
    both = f"{n('s', 'r')} + {n('r', 's')}"
    visited = f"{nr} * (select count(*) from sv) + (select cast(sum(fr * fs) as bigint) from (select d, count(*) as fr from rv group by d) a join (select d, count(*) as fs from sv group by d) b using (d))"
    best = f"best as (select count(*) as n, cast(sum(score) as bigint) as total, cast(max(score) as bigint) as best from (select *, row_number() over (partition by r_id order by score desc, s_id) as rank from pairs) where rank <= {near})"
    steps = "select cast(sum(indexed + scanned + completion_steps) as bigint) from report"
    works = f"works as (select 'exhaustive' as method, {both} as work union all select 'inverted', {visited} union all select 'pruned', ({steps}))"
    return f"select * from (with {sides}, {_work_sql(nr, ns, near)}, {best}, {works} select {values}n, total, best, method, cast(work as bigint) as work from best, works)"


def _first_sql(name: str, n: str) -> str:
    """rv and sv of a pair, cut to the n lowest ids; n over `u`, a fifth of the smaller side."""
    unit = "unit as (select greatest(1, least((select count(distinct id) from ra), (select count(distinct id) from sa)) // 5) as u)"
    low = "select id, d, w from (select *, dense_rank() over (order by id) as place from {0}a), unit where place <= {1}".format
    return f"{pair_sql(name).replace('rv as', 'ra as').replace('sv as', 'sa as')}, {unit}, rv as materialized ({low('r', n)}), sv as materialized ({low('s', n)})"


@query("w1_methods", " union all ".join(_three_sql(_first_sql("supplier_customer", f"{i} * u"), 2, 2, 5, step=i) for i in (1, 3, 5)))
def w1_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Data size in three steps, equal sizes, all methods."""
    r, s = pair(spark, sf_dir, "supplier_customer")
    unit = max(1, min(v.select("id").distinct().count() for v in (r, s)) // 5)
    return _union([_three(_first_ids(r, unit * i), _first_ids(s, unit * i), 5, blocks(2, 2), step=i) for i in (1, 3, 5)])


def _ratio_sql(x: int) -> str:
    cut = "select id, d, w from o, unit where {0}".format
    base = f"v as materialized ({SQL['supplier_part']}), o as (select *, dense_rank() over (order by id) as place from v), unit as (select greatest(1, count(distinct id) // 40) as u from v)"
    return f"{base}, rv as materialized ({cut('place <= 4 * u')}), sv as materialized ({cut(f'place > 4 * u and place <= (4 + {x}) * u')})"


@query("w2_methods", " union all ".join(_three_sql(_ratio_sql(x), 2, 2, 5, ratio=x) for x in (1, 4, 36)))
def w2_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """R fixed at four units, S of one, four and 36 units, all methods."""
    v = vectors(spark, sf_dir, "supplier_part")
    unit = max(1, v.select("id").distinct().count() // 40)
    r = _first_ids(v, 4 * unit)
    top = r.agg(F.max("id")).first()[0] or 0
    return _union([_three(r, _first_ids(v, (4 + x) * unit).where(F.col("id") > top), 5, blocks(2, 2), ratio=x) for x in (1, 4, 36)])


query("w3_methods", " union all ".join(_three_sql(pair_sql("spectrum"), 2, 3, k, k=k) for k in (5, 10, 20)))(lambda s, d: _union([_three(*pair(s, d, "spectrum"), k, blocks(2, 3), k=k) for k in (5, 10, 20)]))

#: Smaller buffers mean more blocks on both sides; R-blocks run side by side here, so R gets the smaller share.
BUFFER_BLOCKS = {0.5: (2, 2), 0.3: (4, 3), 0.1: (10, 6)}
query("w4_methods", " union all ".join(_three_sql(pair_sql("spectrum"), *b, 5, fraction=f) for f, b in BUFFER_BLOCKS.items()))(lambda s, d: _union([_three(*pair(s, d, "spectrum"), 5, blocks(*b), fraction=f) for f, b in BUFFER_BLOCKS.items()]))

# ---------------------------------------------------------------- applications

query("w6_spectrum_search", knn_sql("spectrum").replace("select r_id, s_id, score, cast", "select r_id as query_id, s_id as library_id, score, cast"))(lambda s, d: apps.spectrum_search(*pair(s, d, "spectrum")))

_DOCS = f"v as materialized ({SQL['document_terms']}), lab as (select doc_id as id, quality as label from labels), rv as (select v.* from v join lab on v.id = lab.id where v.id % 5 = 0), sv as (select v.* from v join lab on v.id = lab.id where v.id % 5 <> 0)"
_VOTE = "near as (select r_id, s_id, score from (select *, row_number() over (partition by r_id order by score desc, s_id) as rank from scores) where rank <= 5), votes as (select r_id, label, count(*) as votes, sum(score) as weight from near join lab on s_id = lab.id group by 1, 2), predicted as (select r_id, label as predicted, votes from (select *, row_number() over (partition by r_id order by votes desc, weight desc, label) as place from votes) where place = 1)"
_SCORES = "scores as (select rv.id as r_id, sv.id as s_id, sum(rv.w * sv.w) as score from rv join sv on rv.d = sv.d group by 1, 2)"


def _classified(spark, sf_dir):
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"), F.col("quality").alias("label"))
    v = vectors(spark, sf_dir, "document_terms").join(labels.select("id"), "id", "left_semi")
    return apps.knn_classify(v.where("id % 5 = 0"), v.where("id % 5 <> 0"), labels), labels


query("w7_classify_documents", f"with {_DOCS}, {_SCORES}, {_VOTE} select * from predicted")(lambda s, d: _classified(s, d)[0])


@query("w7_accuracy", f"with {_DOCS}, {_SCORES}, {_VOTE} select count(*) as n, cast(sum(cast(predicted = label as int)) as bigint) as hits from predicted join lab on r_id = lab.id")
def w7_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    predicted, labels = _classified(spark, sf_dir)
    return predicted.join(labels.withColumnRenamed("id", "r_id"), "r_id").agg(F.count("*").alias("n"), F.sum((F.col("predicted") == F.col("label")).cast("int")).alias("hits"))


query("w7_classify_embeddings", f"with v as materialized ({SQL['embedding_positive']}), lab as (select vec_id as id, label from embeddings), rv as (select * from v where id % 5 = 0), sv as (select * from v where id % 5 <> 0), {_SCORES}, {_VOTE} select * from predicted")(
    lambda s, d: apps.knn_classify(vectors(s, d, "embedding_positive").where("id % 5 = 0"), vectors(s, d, "embedding_positive").where("id % 5 <> 0"), table(s, d, "embeddings").select(F.col("vec_id").alias("id"), "label"))
)

_KM = f"v as materialized ({SQL['customer_part']}), c as (select * from v where id in (select distinct id from v order by id limit 5)), scores as (select v.id, c.id as centroid, cast(sum(v.w * c.w) as bigint) as score from v join c on v.d = c.d group by 1, 2), assigned as (select id, centroid, score from (select *, row_number() over (partition by id order by score desc, centroid) as place from scores) where place = 1)"


def _seeds(spark, sf_dir):
    v = vectors(spark, sf_dir, "customer_part")
    return v, _first_ids(v, 5)


query("w8_kmeans_assign", f"with {_KM} select * from assigned")(lambda s, d: apps.kmeans_assign(*_seeds(s, d)))
query("w8_kmeans_step", f"with {_KM} select centroid as id, d, cast(sum(w) as bigint) as w from v join assigned on v.id = assigned.id group by 1, 2")(lambda s, d: apps.kmeans_update(_seeds(s, d)[0], apps.kmeans_assign(*_seeds(s, d))))
query("w8_kmeans_iterate")(lambda s, d: apps.kmeans_iterate(*_seeds(s, d), rounds=3))

# ---------------------------------------------------------------- ablation


_ORDERS = {"frequent_first": "count(*) desc, d", "rare_first": "count(*), d", "natural": "d"}
_STATS = " union all ".join(f"select '{name}' as dim_order, rb, d, count(*) as freq, max(w) as peak_weight, row_number() over (partition by rb order by {by}) as dim_rank from r2 group by rb, d" for name, by in _ORDERS.items())
_W9 = f"""{_FIRST_STATE}, {_LIVE}, stats as ({_STATS}),
  walked as (select dim_order, rb, s3.id as s_id, s3.d, freq, sum(peak_weight * s3.w) over (partition by dim_order, rb, s3.id order by dim_rank, s3.d rows unbounded preceding) as bound from s3 join stats on s3.d = stats.d where sb = 1),
  split as materialized (select dim_order, rule, rb, s_id, d, freq, case rule when 'strict' then bound > block_floor else bound >= block_floor and bound > 0 end as is_tail from walked join floors using (rb), (select unnest(['tie_safe', 'strict']) as rule)),
  visit as (select dim_order, rule, rb, count(*) as indexed_features, cast(sum(freq) as bigint) as scanned_postings from split where is_tail group by 1, 2, 3),
  met as (select distinct dim_order, rule, split.rb, r2.id as r_id, s_id from split join r2 on split.rb = r2.rb and split.d = r2.d where is_tail),
  size as (select id as r_id, count(*) as nr from r2 group by id), head as (select dim_order, rule, rb, s_id, count(*) as nh from split where not is_tail group by 1, 2, 3, 4),
  done as (select dim_order, rule, rb, count(*) as candidates, cast(sum(case when nh is null then 0 else nr + nh end) as bigint) as completion_steps from met join size using (r_id) left join head using (dim_order, rule, rb, s_id) group by 1, 2, 3)
  select dim_order, rule, rb, indexed_features, scanned_postings, coalesce(candidates, 0) as candidates, coalesce(completion_steps, 0) as completion_steps, scanned_postings + coalesce(completion_steps, 0) as steps from visit left join done using (dim_order, rule, rb)"""


@query("w9_ablation", _W9)
def w9_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Indexed features, visited postings, candidates and completion steps of the second S-block under each dimension order and rule."""
    outer, block, kth = _state(spark, sf_dir)
    floors = block_floors(kth, live_vectors(outer, block))
    out = []
    for order in ("frequent_first", "rare_first", "natural"):
        for rule in ("tie_safe", "strict"):
            split = split_features(block, block_dimstats(outer, order), floors, PruneOptions(rule=rule, dim_order=order))
            cost = costs.cost_pruned(outer, split).join(costs.cost_completion(outer, split), "rb", "left").fillna(0, ["candidates", "completion_steps"])
            cost = cost.withColumn("steps", F.col("scanned_postings") + F.col("completion_steps"))
            out.append(cost.select(F.lit(order).alias("dim_order"), F.lit(rule).alias("rule"), "rb", "indexed_features", "scanned_postings", "candidates", "completion_steps", "steps"))
    return _union(out)


# ---------------------------------------------------------------- kernels as functions

_DOT = f"{scores_sql('spectrum')} select r_id, s_id, score from scores"


def _packed_pairs(spark, sf_dir, outer=F.col):
    """r_id, s_id, a, b of all pairs that share a dimension; `outer` makes a from R's packed features, once for each r.

    Where pairs would outgrow a shuffle and R is small enough to go to every task, they are streamed out of cells and none is shuffled.
    """
    r, s = pair(spark, sf_dir, "spectrum")
    grid = inverted.cells(r, s)
    if grid and resident.feature_bytes(r) <= resident.RESIDENT_BYTES:
        a = V.pack(r).select(F.col("id").alias("r_id"), outer("features").alias("a"))
        return met_pairs(r, s, inverted.for_tasks(r, grid)).join(F.broadcast(a), "r_id").select("r_id", "s_id", "a", "b")
    ids = similarity.join_dot(r, s).select("r_id", "s_id")
    a = V.pack(r).select(F.col("id").alias("r_id"), outer("features").alias("a"))
    b = V.pack(s).select(F.col("id").alias("s_id"), F.col("features").alias("b"))
    return ids.join(a, "r_id").join(b, "s_id")


query("dot_merge", _DOT)(lambda s, d: _packed_pairs(s, d).select("r_id", "s_id", similarity.merge_dot(F.col("a"), F.col("b")).alias("score")))
query("dot_probe", _DOT)(lambda s, d: _packed_pairs(s, d, F.map_from_entries).select("r_id", "s_id", similarity.probe_dot(F.col("a"), F.col("b")).alias("score")))
query("dot_join", _DOT)(lambda s, d: every_score(*pair(s, d, "spectrum")))
query("udf_arrow_dot", _DOT)(lambda s, d: _packed_pairs(s, d).select("r_id", "s_id", similarity.merge_dot_arrow("a", "b").alias("score")))
