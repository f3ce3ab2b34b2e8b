"""Laws of vertex lists and update logs, and what the plans must look like."""

from pyspark.sql import functions as F

from vertexlog.functions.reducers import REDUCERS
from vertexlog.operators import algorithms as alg
from vertexlog.operators import vsource
from vertexlog.operators.engines import ENGINES, Engine
from vertexlog.operators.sortreduce import emit_log, first_blocks, fold, partition_log, sorted_log
from vertexlog.operators.updatelog import UpdateLog
from vertexlog.plans import metrics
from vertexlog.sources import layout
from vertexlog.sources.graphs import Graph, partseq, trade
from vertexlog.sources.tables import load


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def lists(spark):
    a = spark.createDataFrame([(1, 10), (2, None), (3, 30)], "v bigint, val bigint")
    b = spark.createDataFrame([(2, 5), (3, 7), (4, 8)], "v bigint, val bigint")
    return a, b


def test_union_takes_the_first_source_even_if_null(spark):
    a, b = lists(spark)
    assert sorted(vsource.union(a, b).collect(), key=lambda r: r[0]) == [(1, 10), (2, None), (3, 30), (4, 8)]


def test_set_laws(spark):
    a, b = lists(spark)
    both = rows(vsource.intersect(a, b).select("v")) + rows(vsource.difference(a, b).select("v"))
    assert sorted(both) == rows(a.select("v"))
    assert rows(vsource.minimum(a, b).where("val is not null")) == [(2, 5), (3, 7)]
    assert rows(vsource.custom(a, b, lambda x, y: x + y, "outer").where("v <> 2")) == [(1, 10), (3, 37), (4, 8)]


def test_compaction_keeps_what_lists_resolve_to(spark):
    log = UpdateLog(spark, "t")
    for step in range(4):
        log.append(step, spark.createDataFrame([(step, step), (9, step)], "v bigint, val bigint"))
    before = rows(log.resolve().select("v", "val"))
    log.compact(2)
    assert rows(log.resolve().select("v", "val")) == before and len(log.lists) == 2


def test_dense_file_seek(spark, tmp_path):
    a, _ = lists(spark)
    vsource.write_dense(a, 6, str(tmp_path / "d"), width=2)
    got = vsource.seek(vsource.dense(spark, str(tmp_path / "d")), 3)
    assert [r[0] for r in rows(got.select("v"))] == [3, 4, 5]


def test_layout_round_trip(spark, tiny, tmp_path):
    x = partseq(spark, tiny)
    layout.build_edges(x.edges, str(tmp_path / "g"), width=64)
    back = layout.read_edges(spark, str(tmp_path / "g"))
    assert rows(back.select("src", "dst", "w")) == rows(x.edges.select("src", "dst", "w"))
    index = spark.read.parquet(str(tmp_path / "g/index"))
    assert rows(layout.out_edges(back, index, [3, 150])) == rows(x.edges.where("src in (3, 150)").select("src", "dst"))
    assert layout.stored_bytes(spark, str(tmp_path / "g")) > 0
    assert sum(b for _, b in layout.stripe((5 << 20) + 7, 3)) == (5 << 20) + 7


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_fold_aggregates_below_its_only_exchange(spark, tiny):
    x = partseq(spark, tiny)
    text = plan(fold(x.edges.select("dst", F.col("w").alias("val")), REDUCERS["sum"]))
    before, _, after = text.partition("Exchange hashpartitioning(dst")
    assert "HashAggregate" in before and "partial_sum" in after
    # sorting first: all records are in order, in files, before anything is folded
    log = x.edges.select("dst", F.col("w").alias("val"))
    assert "Sort [dst" in plan(sorted_log(log)) and "Exchange rangepartitioning(dst" in plan(sorted_log(log))
    read = plan(fold(log, REDUCERS["sum"], "sort_first"))
    assert "FileScan parquet" in read and "lineitem" not in read
    # interleaved: blocks are folded as records are emitted, in no order of destinations
    blocks, count = first_blocks(log, 512, REDUCERS["sum"])
    assert count >= 8 and "rangepartitioning" not in plan(blocks) and rows(blocks.groupBy().sum("val")) == rows(log.groupBy().sum("val"))
    assert "MapInArrow" in plan(fold(log, REDUCERS["sum"], "in_place"))


def test_a_small_frontier_opens_its_ranges_only(spark):
    n = 40_000
    chain = Graph("chain", spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("bigint").alias("w")), n).stored(width=1000)
    engine = Engine()
    edges = engine.prepare(chain)
    active = spark.createDataFrame([(5, 5), (17_003, 1)], "v bigint, val bigint")
    done = engine.round(active, edges, F.col("src"), "min", 2)
    assert "PartitionFilters: [isnotnull(src_part#" in plan(done) or "src_part#" in plan(done).partition("PartitionFilters: [")[2].partition("]")[0]
    assert engine.opened == [[0, 17]]
    used = metrics.stage_totals(spark, lambda: done.collect())
    assert rows(done) == [(6, 5), (17_004, 17_003)]
    assert 2 <= used["rows_read"] <= 2000
    # values of a few vertices come from the lists' own ranges
    log = UpdateLog(spark, "t", 1000)
    for step in range(3):
        log.append(step, spark.range(n).select(F.col("id").alias("v"), (F.col("id") + step).alias("val")))
    some = log.resolve(active.select("v"))
    assert metrics.stage_totals(spark, lambda: some.collect())["rows_read"] <= 6000 and rows(some.select("v", "val")) == [(5, 7), (17_003, 17_005)]
    near = Graph("part", chain.edges.where("src < 1500"), n, 1000)
    assert alg.sssp(near, 1495).count() == 6
    tree = alg.bfs(near, 1400)
    assert len(tree.sizes) == 101 and tree.opened[0] == [1] and max(map(len, tree.opened)) == 1 and max(tree.edges_read(near)) <= 1000


def test_engines_hold_no_cache_and_scan_by_partitions(spark, tiny):
    x = partseq(spark, tiny).stored()
    alg.rank_fixed(x, 1, engine=ENGINES["cached"]())
    assert spark.sparkContext._jsc.getPersistentRDDs().isEmpty()
    e = ENGINES["edge_scan"](memory=x.n * 16 // 4)
    assert rows(alg.rank_fixed(x, 2, engine=e)) == rows(alg.rank_fixed(x, 2)) and e.partitions == 4


def test_approximate_counts_and_sketch_errors(spark, tiny):
    from vertexlog.plans.registry import QUERIES

    got, edges = QUERIES["approx_reach"](spark, tiny).first(), trade(spark, tiny).edges
    for column, name in (("dst", "dsts"), ("src", "srcs")):
        exact = edges.select(column).distinct().count()
        assert abs(got[name] - exact) <= 0.15 * exact


def test_small_frontier_is_broadcast_and_filters_reach_the_scan(spark, tiny):
    edges = load(spark, tiny, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))
    active = spark.createDataFrame([(1, 1)], "v bigint, val bigint")
    assert "BroadcastHashJoin" in plan(emit_log(active, edges, F.col("val"), broadcast_active=True))
    text = plan(edges.where("src > 5"))
    assert "GreaterThan(l_partkey,5)" in text and "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint>" in text


def test_ranges_of_a_partitioned_log_need_no_second_exchange(spark, tiny):
    x = partseq(spark, tiny)
    text = plan(partition_log(x.edges.select("dst", "w"), 50, 4))
    assert text.count("Exchange") >= 1


def test_bucketed_edges_fold_and_join_without_exchange(spark, tmp_path):
    edges = spark.range(4000).selectExpr("id % 97 as src", "id % 89 as dst", "id as w")
    a, b = (layout.write_bucketed(edges, str(tmp_path / name), "dst", 8) for name in ("a", "b"))
    folded = a.groupBy("dst").agg(F.sum("w").alias("t"))
    joined = folded.join(b.hint("merge"), "dst").groupBy("dst").agg(F.count("*").alias("n"))
    plan = joined._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "SortMergeJoin" in plan
    assert sorted(map(tuple, joined.collect())) == sorted(map(tuple, edges.groupBy("dst").count().collect()))
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("bucketed_")]
