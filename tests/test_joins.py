"""The join methods on a hand example, random vectors, edge cases and plans."""

import random

import pytest
from pyspark.sql import functions as F

from sparse_neighbors.functions import similarity
from sparse_neighbors.functions import vectors as V
from sparse_neighbors.operators import costs
from sparse_neighbors.operators.exhaustive import exhaustive_grid, exhaustive_join
from sparse_neighbors.operators.inverted import inverted_join, inverted_packed
from sparse_neighbors.operators.costs import cost_completion
from sparse_neighbors.operators.pruned import PruneOptions, block_dimstats, split_features
from sparse_neighbors.plans.api import explain_join, knn_join
from sparse_neighbors.plans.blocks import BlockPlan, assign_blocks, plan_sizes
from sparse_neighbors.plans.nested_loop import block_join, join_report
from sparse_neighbors.sources.datasets import pair

R0 = {1: {1: 2, 3: 1}, 2: {2: 1, 3: 2, 5: 1}, 3: {6: 1}}
S0 = {1: {1: 1, 3: 1}, 2: {2: 3, 3: 1}, 3: {3: 2, 5: 2}, 4: {1: 1, 4: 5}, 5: {4: 7}, 6: {3: 1, 5: 1}}


def frame(spark, v):
    return spark.createDataFrame([(i, d, w) for i, f in v.items() for d, w in f.items()], "id long, d long, w long")


def rows(df):
    return sorted(tuple(x) for x in df.select("r_id", "s_id", "score").collect())


def expected(r, s, k, ties="id"):
    out = []
    for i, a in r.items():
        scores = [(sum(w * b.get(d, 0) for d, w in a.items()), j) for j, b in s.items()]
        scores = sorted(((x, j) for x, j in scores if x > 0), key=lambda t: (-t[0], t[1]))
        if ties == "id":
            kept = scores[:k]
        else:
            above = {x: sum(y > x for y, _ in scores) for x, _ in scores}
            equal = {x: sum(y == x for y, _ in scores) for x, _ in scores}
            kept = [t for t in scores if above[t[0]] < k and (ties == "all" or above[t[0]] + equal[t[0]] <= k)]
        out += [(i, j, x) for x, j in kept]
    return sorted(out)


def random_vectors(rng, n, dims, nnz):
    return {i: {rng.randrange(dims): rng.randint(1, 9) for _ in range(rng.randint(1, nnz))} for i in range(n)}


@pytest.mark.parametrize("ties", ["id", "all", "strict"])
def test_hand_example(spark, ties):
    r, s = frame(spark, R0), frame(spark, S0)
    want = expected(R0, S0, 2, ties)
    assert rows(inverted_join(r, s, 2, ties)) == want
    assert rows(exhaustive_join(r, s, 2, ties)) == want
    assert rows(knn_join(r, s, 2, "pruned", ties=ties, plan=BlockPlan(0, 0, 1, 2))) == want


def test_hand_example_costs(spark):
    r, s = frame(spark, R0), frame(spark, S0)
    assert costs.cost_exhaustive(r, s).first()["c2"] == 69
    assert costs.cost_inverted(r, s).first()["c3"] == 24
    assert explain_join(r, s).first()["method"] == "inverted"


def test_hand_example_split(spark):
    outer = frame(spark, {i: R0[i] for i in (1, 2)}).select(F.lit(0).alias("rb"), F.col("id").alias("r_id"), "d", "w")
    stats = block_dimstats(outer)
    assert [x["d"] for x in stats.orderBy("dim_rank").collect()] == [3, 1, 2, 5]
    block = frame(spark, {i: S0[i] for i in (4, 5, 6)}).withColumnRenamed("id", "s_id")
    floors = spark.createDataFrame([(0, 2)], "rb int, block_floor long")
    tails = {rule: {(x["s_id"], x["d"]) for x in split_features(block, stats, floors, PruneOptions(rule=rule)).where("is_tail").collect()} for rule in ("strict", "tie_safe")}
    assert tails == {"strict": {(6, 5)}, "tie_safe": {(4, 1), (6, 3), (6, 5)}}


@pytest.mark.parametrize("seed", [1, 2])
def test_methods_agree_on_random_vectors(spark, seed):
    rng = random.Random(seed)
    a, b, k = random_vectors(rng, 40, 25, 6), random_vectors(rng, 60, 25, 6), rng.choice([1, 3, 70])
    r, s, want = frame(spark, a), frame(spark, b), expected(a, b, k)
    assert rows(inverted_join(r, s, k)) == want
    assert rows(inverted_packed(r, s, k, heavy=5)) == want
    assert rows(exhaustive_grid(r, s, k, 2, 3)) == want
    plan = BlockPlan(0, 0, 2, 3)
    assert rows(block_join(r, s, k, "pruned", plan, s_how="hash", order=[2, 0, 1])) == want
    assert rows(block_join(r, s, k, "pruned", plan, PruneOptions(rule="strict", drop_dead=False))) == want
    assert rows(block_join(r, s, k, "pruned", plan, PruneOptions(precheck=True, dim_order="rare_first"))) == want


def test_fractional_weights_near_the_floor(spark):
    rng = random.Random(5)
    a = {i: {d: w / 7 for d, w in f.items()} for i, f in random_vectors(rng, 20, 12, 5).items()}
    b = {i: {d: w / 3 for d, w in f.items()} for i, f in random_vectors(rng, 30, 12, 5).items()}
    make = lambda v: spark.createDataFrame([(i, d, float(w)) for i, f in v.items() for d, w in f.items()], "id long, d long, w double")
    r, s = make(a), make(b)
    one = inverted_join(r, s, 3).groupBy("r_id").agg(F.round(F.sum("score"), 6).alias("x"))
    two = block_join(r, s, 3, "pruned", BlockPlan(0, 0, 2, 3)).groupBy("r_id").agg(F.round(F.sum("score"), 6).alias("x"))
    assert one.exceptAll(two).count() == 0 and two.exceptAll(one).count() == 0


def test_kth_scores_never_fall_and_candidates_shrink(spark):
    rng = random.Random(9)
    r, s = frame(spark, random_vectors(rng, 30, 15, 5)), frame(spark, random_vectors(rng, 60, 15, 5))
    states = []
    block_join(r, s, 3, "pruned", BlockPlan(0, 0, 2, 3), report=states)
    worst = [{x["r_id"]: x["m"] for x in st.groupBy("r_id").agg(F.min("score").alias("m")).collect()} for st in states]
    full = {x["r_id"] for x in states[0].groupBy("r_id").count().where("count = 3").collect()}
    for before, after in zip(worst, worst[1:], strict=False):
        assert all(after[i] >= before[i] for i in full)


def test_empty_sides_and_missing_matches(spark):
    r, nothing = frame(spark, R0), frame(spark, S0).where("false")
    assert rows(inverted_join(r, nothing, 2)) == [] and rows(inverted_join(nothing, r, 2)) == []
    assert rows(block_join(r, nothing, 2, "pruned", BlockPlan(0, 0, 1, 2))) == []
    assert rows(exhaustive_join(r, nothing, 2)) == []
    padded = knn_join(r, frame(spark, S0), 2, "inverted", fill_zero=True)
    assert rows(padded.where("r_id = 3")) == [(3, 1, 0), (3, 2, 0)]


def test_exclude_self_and_cosine(spark):
    s = frame(spark, S0)
    assert all(x["r_id"] != x["s_id"] for x in knn_join(s, s, 2, "inverted", exclude_self=True).collect())
    best = knn_join(s, s, 1, "inverted", metric="cosine").where("r_id = 6").first()
    assert best["s_id"] in (3, 6) and abs(best["score"] - 1) < 1e-9


def test_strict_rule_needs_ascending_blocks(spark):
    r, s = frame(spark, R0), frame(spark, S0)
    with pytest.raises(ValueError):
        block_join(r, s, 2, "pruned", BlockPlan(0, 0, 1, 2), PruneOptions(rule="strict"), s_how="hash")


def test_validation(spark):
    with pytest.raises(ValueError):
        V.validate_vectors(frame(spark, {1: {1: -2}}))
    assert V.validate_vectors(frame(spark, {1: {1: -2, 2: 1}}), "clip").count() == 1
    with pytest.raises(ValueError):
        V.validate_vectors(frame(spark, S0).unionAll(frame(spark, S0)))
    merged = V.from_long(frame(spark, S0).unionAll(frame(spark, S0)), "id", "d", "w", "max")
    assert rows(inverted_join(frame(spark, R0), merged, 2)) == expected(R0, S0, 2)


def test_dot_forms(spark):
    p = V.pack(frame(spark, S0))
    pairs = p.select(F.col("features").alias("a")).crossJoin(p.select(F.col("features").alias("b")))
    got = pairs.select(similarity.merge_dot(F.col("a"), F.col("b")).alias("m"), similarity.probe_dot(F.map_from_entries("a"), F.col("b")).alias("p"), similarity.merge_dot_arrow("a", "b").alias("w"))
    assert got.where("m <> p or m <> w").count() == 0


@pytest.mark.parametrize("how", ["range", "geometric", "mod", "hash"])
def test_blocks_cover_every_vector_once(spark, how):
    v = V.synthetic_vectors(spark, 300, 50, 4)
    b = assign_blocks(v, 4, how)
    per_id = b.groupBy("id").agg(F.countDistinct("block").alias("n"), F.first("block").alias("b"))
    assert per_id.where("n > 1").count() == 0 and per_id.count() == 300 and b.where("block < 0 or block > 3").count() == 0
    if how == "range":
        limits = per_id.groupBy("b").agg(F.min("id").alias("a"), F.max("id").alias("z")).orderBy("b").collect()
        assert all(x["z"] < y["a"] for x, y in zip(limits, limits[1:], strict=False))


def test_default_plans():
    """Equal sizes under the defaults: two blocks of R, five of S; less buffer means more pages read."""
    plan = plan_sizes(682_667, 682_667)
    assert (plan.r_blocks, plan.s_blocks) == (2, 5)
    pages = [plan_sizes(100_000, 590_000, f).io_pages for f in (0.5, 0.4, 0.3, 0.2, 0.1)]
    assert pages == sorted(pages)
    assert plan_sizes(100_000, 590_000, layout="classic").s_blocks > plan_sizes(100_000, 590_000).s_blocks


def test_plans_have_no_cross_product_and_limit_groups_early(spark):
    r, s = frame(spark, R0), frame(spark, S0)
    text = inverted_join(r, s, 2)._jdf.queryExecution().toString()
    assert "Cartesian" not in text and "NestedLoop" not in text and "WindowGroupLimit" in text
    text = inverted_join(r, s, 2, "all")._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in text


def test_scan_reads_only_what_it_needs(spark, data):
    from sparse_neighbors.sources.datasets import vectors

    text = vectors(spark, data, "order_part")._jdf.queryExecution().toString()
    assert "l_extendedprice" not in text.split("== Physical Plan ==")[1]


def test_completion_counts_merges_with_heads(spark):
    r = spark.createDataFrame([(0, 1, 5, 1), (0, 1, 6, 1), (0, 2, 6, 1), (1, 3, 6, 1)], "rb int, r_id long, d long, w long")
    split = spark.createDataFrame([(0, 8, 5, False), (0, 8, 6, True), (0, 9, 6, True), (1, 8, 6, False)], "rb int, s_id long, d long, is_tail boolean")
    # block 0: r 1 and 2 each meet s 8 (a head of 1) and s 9 (none); block 1 has no indexed feature
    assert [tuple(x) for x in cost_completion(r, split).collect()] == [(0, 4, (2 + 1) + (1 + 1))]


@pytest.mark.parametrize("ties", ["id", "all", "strict"])
def test_every_method_takes_every_option(spark, ties):
    """A set joined with itself, with fractional weights: cosine, ties and exclude_self mean the same to all methods."""
    from sparse_neighbors.plans.api import knn_join

    v = frame(spark, random_vectors(random.Random(12), 25, 12, 4))
    digest = lambda df: sorted((x["r_id"], x["s_id"], round(float(x["score"]), 6)) for x in df.collect())
    want = digest(knn_join(v, v, 3, "inverted", ties=ties, exclude_self=True))
    assert want and all(r != s for r, s, _ in want)
    for method in ("packed", "exhaustive", "grid"):
        assert digest(knn_join(v, v, 3, method, ties=ties, exclude_self=True)) == want
    assert digest(knn_join(v, v, 3, "pruned", ties=ties, exclude_self=True, plan=BlockPlan(0, 0, 2, 2))) == want


def test_grid_scores_keep_fractions_and_padding_leaves_self_out(spark):
    from sparse_neighbors.plans.api import knn_join

    v = frame(spark, random_vectors(random.Random(13), 20, 30, 3))
    digest = lambda df: sorted((x["r_id"], x["rank"], round(x["score"], 9)) for x in df.collect())
    grid = digest(knn_join(v, v, 2, "grid", metric="cosine"))
    assert grid == digest(knn_join(v, v, 2, "inverted", metric="cosine")) and any(0 < s < 0.999 for *_, s in grid)
    filled = knn_join(v, v, 4, "inverted", exclude_self=True, fill_zero=True).collect()
    assert len(filled) == 4 * v.select("id").distinct().count() and all(x["r_id"] != x["s_id"] for x in filled)


def test_measures_of_a_run(spark):
    from sparse_neighbors.plans.metering import Cost, measure, measure_query, percent_better, speed_up

    cost = measure_query(spark, lambda: spark.range(0, 100_000, 1, 4).groupBy((F.col("id") % 7).alias("g")).count())
    assert cost.wall_seconds > 0 and cost.cpu_seconds > 0 and cost.shuffle_bytes > 0 and cost.stages >= 2
    nothing = measure(spark, lambda: None)
    assert nothing.stages == 0 and nothing.io_bytes == 0
    slow, fast = (Cost(1.0, x, 0, 0, 0, 0, 1) for x in (10.0, 4.0))
    assert speed_up(slow, fast) == 2.5 and percent_better(slow, fast) == 60.0 and percent_better(fast, slow) == -150.0


def test_no_blocks_give_no_rows(spark, data):
    r, s = pair(spark, data, "spectrum")
    assert block_join(r, s, 3, "pruned", BlockPlan(0, 0, 2, 2), order=[]).count() == 0


def test_report_rows_cover_the_work(spark, data):
    r, s = pair(spark, data, "spectrum")
    rows = join_report(r, s, 3, BlockPlan(0, 0, 1, 2)).collect()
    assert {x["sb"] for x in rows} == {0, 1}
    assert sum(x["scanned"] for x in rows) <= costs.summary(r, s).first()["products"]
    assert all(x["completed"] <= x["candidates"] <= x["scanned"] for x in rows)


@pytest.mark.parametrize("ties", ["id", "all", "strict"])
def test_resident_form(spark, ties):
    """One broadcast of R or several, with every tie rule; and the pruned loop with R sent to every task or not."""
    from sparse_neighbors.operators.resident import resident_join

    rng = random.Random(14)
    rv, sv = random_vectors(rng, 20, 15, 5), random_vectors(rng, 50, 15, 5)
    r, s = frame(spark, rv), frame(spark, sv)
    want = expected(rv, sv, 3, ties)
    assert rows(resident_join(r, s, 3, ties)) == want
    assert rows(resident_join(r, s, 3, ties, block_bytes=32 * 20)) == want
    if ties != "strict":
        for size in (0, 1 << 20):
            assert rows(block_join(r, s, 3, "pruned", BlockPlan(0, 0, 2, 3), ties=ties, resident_bytes=size)) == want
            assert rows(block_join(r, s, 3, "inverted", BlockPlan(0, 0, 2, 3), ties=ties, resident_bytes=size)) == want


def test_resident_form_shuffles_no_partial_sums(spark, tmp_path):
    from sparse_neighbors.operators.resident import resident_join

    frame(spark, S0).write.parquet(str(tmp_path / "s"))
    plan = resident_join(frame(spark, R0), spark.read.parquet(str(tmp_path / "s")), 2)._jdf.queryExecution().executedPlan().toString()
    # S by its id, the distinct dimensions of R, the ranks by r
    assert plan.count("Exchange hashpartitioning") == 3 and "Exchange hashpartitioning(r_id" in plan and "SortMergeJoin" not in plan


def test_resident_form_of_odd_sides(spark):
    from sparse_neighbors.operators.resident import feature_bytes, resident_join

    none = spark.createDataFrame([], "id long, d long, w long")
    s = frame(spark, S0)
    assert feature_bytes(none) == 0
    assert resident_join(none, s, 2).count() == 0 and resident_join(s, none, 2).count() == 0
    with pytest.raises(ValueError):
        knn_join(s, s, 2, "packed", strategy="resident")
    with pytest.raises(ValueError):
        knn_join(s, s, 2, strategy="other")


def test_choice_of_strategy():
    """Small or thin joins shuffle by dimension; dense ones broadcast R while few blocks hold it, and else take the pruned loop."""
    from sparse_neighbors.plans.api import _choice

    n = {"r_features": 10**6, "s_features": 10**9, "products": 10**9}
    assert _choice(n | {"s_features": 10**6, "products": 10**12}) == ("inverted", "dimension")
    assert _choice(n) == ("inverted", "dimension")
    assert _choice(n | {"products": 10**13}) == ("inverted", "resident")
    assert _choice(n | {"products": 10**15, "r_features": 10**9}) == ("pruned", "dimension")


def test_arrays_of_candidates_merge(spark):
    from sparse_neighbors.operators.topk import from_best, merge_best, to_best

    make = lambda x: to_best(spark.createDataFrame(x, "r_id long, s_id long, score long"))
    a, b = make([(1, 5, 9), (1, 4, 7), (2, 1, 3)]), make([(1, 2, 7), (1, 3, 8), (3, 1, 1)])
    both = a.join(b.withColumnRenamed("best", "other"), "r_id", "full").select("r_id", merge_best(F.col("best"), F.col("other"), 3).alias("best"))
    assert sorted(tuple(x) for x in from_best(both).collect()) == [(1, 2, 7, 3), (1, 3, 8, 2), (1, 5, 9, 1), (2, 1, 3, 1), (3, 1, 1, 1)]

