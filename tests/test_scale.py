"""Forms that hold at size, on small data: cells, merged blocks, bounded broadcasts, state on disk."""

import pytest
from pyspark.sql import functions as F

from sparse_neighbors.operators import inverted, pruned, resident
from sparse_neighbors.plans import nested_loop
from sparse_neighbors.plans.blocks import BlockPlan
from sparse_neighbors.queries import joins, relational, streams


@pytest.mark.parametrize("ties", ["id", "all", "strict"])
def test_cells_give_the_join_by_partial_sums(spark, monkeypatch, ties):
    """Sides whose dimensions are frequent go through cells, with no sum of a pair shuffled, and give the same rows."""
    r = spark.range(400).select(F.expr("id % 20 as id"), F.expr("id % 13 * 7 as d"), F.expr("id % 3 + 1 as w")).groupBy("id", "d").agg(F.sum("w").alias("w"))
    s = r.select((F.col("id") + 5).alias("id"), "d", "w")
    want = sorted(map(tuple, inverted.inverted_join(r, s, 3, ties, True).collect()))
    assert inverted.cells(r, s) is None
    monkeypatch.setattr(inverted, "MOST_SUMS", 0)
    monkeypatch.setattr(inverted, "S_CELL", 100)
    assert inverted.cells(r, s) == (1, 3)
    got = inverted.inverted_join(r, s, 3, ties, True)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "InArrow" in plan and "sum(" not in plan.split("InArrow")[0]
    assert sorted(map(tuple, got.collect())) == want and want


def test_state_comes_from_the_inverted_join(spark, data, monkeypatch):
    """The k-th scores after the first S-block come from rows cut to k before any shuffle by pair."""
    plain = sorted(map(tuple, joins.QUERIES["kth_scores"](spark, data).collect()))
    asked = []
    monkeypatch.setattr(inverted, "MOST_SUMS", 0)
    monkeypatch.setattr(inverted, "cell_join", lambda *a, f=inverted.cell_join: asked.append(a[2]) or f(*a))
    monkeypatch.setattr(inverted, "cells", lambda r, s: (2, 2))
    assert sorted(map(tuple, joins.QUERIES["kth_scores"](spark, data).collect())) == plain and asked == [2]


def test_synthetic_vectors_come_from_a_given_table(spark, data):
    """A vector for each customer, from Spark's own reading of the table."""
    n = spark.read.parquet(f"{data}/customer.parquet").count()
    assert [tuple(r) for r in joins.QUERIES["vec_synthetic"](spark, data).collect()] == [(n, True)] and n != 200


def test_large_sides_are_not_broadcast(spark):
    orders = spark.range(50)
    assert relational._broadcast_hint(orders, 50) == "broadcast" and relational._broadcast_hint(orders, 49) == "shuffle_hash"


def test_theta_pairs_only_prices_with_a_partner(spark):
    """Sizes whose prices are too close are not paired at all; all others give every pair."""
    rows = [(i, i % 4, float(900 + (i * 37 % 100) + (1000 if i % 4 == 1 and i % 3 == 0 else 0))) for i in range(80)] + [(99, 1, None)]
    got = relational._theta(spark.createDataFrame(rows, "p_partkey long, p_size int, p_retailprice double"))
    want = sorted((a, b) for a, n, x in rows for b, m, y in rows if n == m and x is not None and y is not None and x > y + 500)
    assert sorted(map(tuple, got.collect())) == want and want
    assert "min(" in got._jdf.queryExecution().executedPlan().toString()


def test_orders_that_tie_in_price_give_the_lowest_key(spark):
    rows = [(7, 1, 5.0), (3, 1, 5.0), (9, 1, 2.0), (4, 1, 2.0), (1, 1, None), (None, 1, 9.0), (5, 2, None)]
    for part in (rows, rows[::-1]):
        got = relational._dearest(spark.createDataFrame(part, "o_orderkey long, o_custkey long, o_totalprice double").repartition(3))
        assert sorted(map(tuple, got.collect())) == [(1, 3, 4), (2, None, None)]


def test_deduplication_keeps_its_state_on_disk(spark, data, monkeypatch):
    """The stream runs with the RocksDB provider and the session's own is back afterwards."""
    from sparse_neighbors.streaming import streams as running

    before, seen = spark.conf.get(running.PROVIDER), []
    monkeypatch.setattr(running, "run_to_end", lambda w, provider="", f=running.run_to_end: (seen.append(provider), f(w, provider)))
    rows = streams.QUERIES["st_dedup"](spark, data).agg(F.sum("n")).first()[0]
    assert rows == spark.read.parquet(f"{data}/events.parquet").count() and seen == [running.ROCKSDB] and spark.conf.get(running.PROVIDER) == before


def test_resident_blocks_are_merged_and_follow_each_other(spark, data, monkeypatch):
    """A small block size gives no more scans than MOST_SCANS; results of blocks are files, so no broadcast waits in the plan."""
    big = resident.RESIDENT_BYTES
    assert resident.block_count(10**8, 1 << 18) == resident.MOST_SCANS and resident.block_count(10, 1 << 18) == 1
    assert resident.block_count(20 * big, 1 << 18) == 20 and resident.block_count(3 * big, big) == 3
    monkeypatch.setattr(resident, "MOST_SCANS", 3)
    r, s = joins.pair(spark, data, "customer")
    got = resident.resident_join(r, s, block_bytes=4000)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and plan.count("FileScan") == 3
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, inverted.inverted_join(r, s).collect()))


def test_sessions_stay_off_the_driver(spark, data, monkeypatch):
    """The complete table goes to a folder a batch, and the last one holds each session once."""
    monkeypatch.setattr(streams.streams, "collect_stream", lambda *a: pytest.fail("the driver's memory takes the sessions"))
    got = streams.QUERIES["st_session"](spark, data)
    assert got.columns == ["user_id", "start", "n"] and got.count() == got.dropDuplicates(["user_id", "start"]).count()
    assert got.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{data}/events.parquet").count()


def test_the_state_stream_holds_candidates_of_cells(spark, monkeypatch):
    """Sides with frequent dimensions send k scores per r and cell, which have the k best among them."""
    r = spark.range(400).select(F.expr("id % 20 as id"), F.expr("id % 13 * 7 as d"), F.expr("id % 3 + 1 as w")).groupBy("id", "d").agg(F.sum("w").alias("w"))
    s = r.select((F.col("id") + 5).alias("id"), "d", "w")
    every = inverted.candidate_scores(r, s, 3)
    want = sorted(map(tuple, inverted.top_k(every, 3).collect()))
    monkeypatch.setattr(inverted, "MOST_SUMS", 0)
    monkeypatch.setattr(inverted, "S_CELL", 100)
    few = inverted.candidate_scores(r, s, 3)
    assert sorted(map(tuple, inverted.top_k(few, 3).collect())) == want and few.count() <= 20 * 3 * 3 < every.count()


def in_cells(monkeypatch):
    """Every join with cells of a few features, and none that adds up or counts pairs by a shuffle."""
    from sparse_neighbors.streaming import streams as running

    monkeypatch.setattr(inverted, "MOST_SUMS", -1)
    monkeypatch.setattr(inverted, "R_CELL", 60)
    monkeypatch.setattr(inverted, "S_CELL", 500)
    monkeypatch.setattr(inverted, "cells", lambda r, s, f=inverted.cells: f(r, s) and (2, 3))
    for module, name in ((nested_loop, "cells"), (running, "cells")):
        monkeypatch.setattr(module, name, lambda r, s: (2, 3))
    for module, name in ((pruned, "partial_scores"), (nested_loop, "accumulate"), (running, "accumulate")):
        monkeypatch.setattr(module, name, lambda *a, n=name, **o: pytest.fail(f"{n} shuffles sums of pairs"))


@pytest.mark.parametrize("name", ["knn_pruned_keep_dead", "knn_pruned_ties_all", "knn_pruned_ties_strict", "join_report", "theorem_missed_pairs"])
def test_later_blocks_go_through_cells(spark, data, monkeypatch, name):
    """Scores and counts of all S-blocks come out of cells, and are those of the partial sums."""
    want = sorted(map(tuple, joins.QUERIES[name](spark, data).collect()))
    in_cells(monkeypatch)
    assert sorted(map(tuple, joins.QUERIES[name](spark, data).collect())) == want and want


def test_completions_are_counted_in_cells(spark, data, monkeypatch):
    want = sorted(map(tuple, joins.QUERIES["cost_completion"](spark, data).collect()))
    monkeypatch.setattr(inverted, "cells", lambda r, s, most=None: (2, 3))
    got = joins.QUERIES["cost_completion"](spark, data)
    assert "InArrow" in got._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, got.collect())) == want and want


def test_a_stream_of_blocks_goes_through_cells(spark, data, monkeypatch):
    want = sorted(map(tuple, streams.QUERIES["st_inner_join"](spark, data).collect()))
    in_cells(monkeypatch)
    assert sorted(map(tuple, streams.QUERIES["st_inner_join"](spark, data).collect())) == want and want


@pytest.mark.parametrize("weight", ["id % 3 + 1", "(id % 3 + 1) / 4.0", "id % 3"])
def test_cells_take_any_weights_and_leave_out_self(spark, monkeypatch, weight):
    r = spark.range(700).select(F.expr("id % 20 as id"), F.expr("id % 13 * 7 as d"), F.expr(f"{weight} as w")).groupBy("id", "d").agg(F.sum(F.col("w").cast("double" if "/" in weight else "long")).alias("w"))
    s = r.select((F.col("id") + 5).alias("id"), "d", "w")
    plan = BlockPlan(0, 0, 2, 3)

    def rows():
        found = nested_loop.block_join(r, s, 3, "pruned", plan, exclude_self=True).collect()
        return sorted((x.r_id, x.s_id, round(x.score, 9), x.rank) for x in found)

    want = rows()
    in_cells(monkeypatch)
    assert rows() == want and want


@pytest.mark.parametrize("weight", ["id % 3 + 1", "(id % 3 + 1) / 4.0", "id % 3 - 1"])
def test_all_pairs_are_streamed_out_of_cells(spark, monkeypatch, weight):
    """Every pair that shares a dimension comes once, whatever its score, and nothing is shuffled by pair; vectors may span batches."""
    r = spark.range(700).select(F.expr("id % 20 as id"), F.expr("id % 13 * 7 as d"), F.expr(f"{weight} as w")).groupBy("id", "d").agg(F.sum(F.col("w").cast("double" if "/" in weight else "long")).alias("w"))
    r = r.unionByName(r.limit(1).select(F.lit(99).alias("id"), F.lit(1).alias("d"), "w"))
    s = r.where("d > 7").select((F.col("id") + 5).alias("id"), "d", "w")
    want = sorted(map(tuple, inverted.every_score(r, s).collect()))
    own = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    monkeypatch.setattr(inverted, "MOST_SUMS", -1)
    monkeypatch.setattr(inverted, "cells", lambda r, s: (2, 3))
    monkeypatch.setattr(inverted, "join_dot", lambda *a: pytest.fail("sums of pairs are shuffled"))
    monkeypatch.setattr("sparse_neighbors.operators.pair_cells.PAIRS", 50)
    try:
        for rows in ("7", "10000"):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
            assert sorted(map(tuple, inverted.every_score(r, s).collect())) == want and want
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", own)


def test_dot_join_goes_through_cells(spark, data, monkeypatch):
    want = sorted(map(tuple, joins.QUERIES["dot_join"](spark, data).collect()))
    monkeypatch.setattr(inverted, "cells", lambda r, s: (2, 3))
    got = joins.QUERIES["dot_join"](spark, data)
    assert "InArrow" in got._jdf.queryExecution().executedPlan().toString() and got.columns == ["r_id", "s_id", "score"]
    assert sorted(map(tuple, got.collect())) == want and want


@pytest.mark.parametrize("weight", ["id % 3 + 1", "(id % 3 + 1) / 4.0"])
def test_every_candidate_is_streamed_out_of_cells(spark, monkeypatch, weight):
    """The candidates of both R-blocks and their whole scores, heads added, come out of cells; vectors may span batches."""
    kind = "double" if "/" in weight else "long"
    r = spark.range(700).select(F.expr("cast(id % 20 div 10 as int) as rb"), F.expr("id % 20 as r_id"), F.expr("id % 13 * 7 as d"), F.expr(f"{weight} as w")).groupBy("rb", "r_id", "d").agg(F.sum(F.col("w").cast(kind)).alias("w"))
    s = r.where("d > 7 and (r_id + d) % 4 > 0").select((F.col("r_id") + 5).alias("s_id"), "d", "w")
    kth = r.select("rb", "r_id").distinct().withColumn("kth_score", F.lit(100 if kind == "long" else 6).cast(kind))

    def rows(**how):
        found = pruned.pruned_block(r, s, kth, pruned.block_dimstats(r), pruned.PruneOptions(precheck=False), **how)
        return sorted((x.rb, x.r_id, x.s_id, round(x.score, 6)) for x in found.select("rb", "r_id", "s_id", "score").collect())

    want = rows()
    heads = pruned.split_features(s, pruned.block_dimstats(r), pruned.block_floors(kth)).where("not is_tail").count()
    own = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    monkeypatch.setattr(pruned, "partial_scores", lambda *a: pytest.fail("sums of pairs are shuffled"))
    monkeypatch.setattr("sparse_neighbors.operators.pair_cells.PAIRS", 50)
    try:
        for size in ("7", "10000"):
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
            assert rows(grid=(2, 3), every=True) == want and want and heads
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", own)


def test_pruned_candidates_goes_through_cells(spark, data, monkeypatch):
    want = sorted(map(tuple, joins.QUERIES["pruned_candidates"](spark, data).collect()))
    monkeypatch.setattr(inverted, "cells", lambda r, s, most=None: (2, 3))
    got = joins.QUERIES["pruned_candidates"](spark, data)
    assert "InArrow" in got._jdf.queryExecution().executedPlan().toString() and got.columns == ["rb", "r_id", "s_id", "score"]
    assert sorted(map(tuple, got.collect())) == want and want


@pytest.mark.parametrize("name", ["dot_probe", "dot_merge", "udf_arrow_dot"])
def test_packed_pairs_are_not_shuffled(spark, data, monkeypatch, name):
    """Pairs leave the cells with the features of s, and R's packed features are broadcast: the exchanges are below the cells and for R."""
    from sparse_neighbors.operators import pair_cells

    want = sorted(map(tuple, joins.QUERIES[name](spark, data).collect()))
    monkeypatch.setattr(inverted, "cells", lambda r, s, most=None: (2, 3))
    monkeypatch.setattr(pair_cells, "PAIRS", 50)
    monkeypatch.setattr(joins.similarity, "join_dot", lambda *a: pytest.fail("pairs are shuffled"))
    got = joins.QUERIES[name](spark, data)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan
    assert sorted(map(tuple, got.collect())) == want and want
