"""Six vertices by hand, and the edge cases around them."""

import pytest
from pyspark.sql import functions as F

from vertexlog.functions.reducers import REDUCERS, check_associative, custom
from vertexlog.operators import algorithms as alg
from vertexlog.operators import local
from vertexlog.operators.engines import ENGINES, CapacityExceeded, Engine, SemiExternal
from vertexlog.operators.sortreduce import MODES, fold, merge_phases, merge_plan, merge_schedule, merge_tree
from vertexlog.plans import cost, metrics
from vertexlog.sources.graphs import Graph, kron_edges
from vertexlog.sources.kron_source import kron_edge
from vertexlog.sources.tables import ordinal

EDGES = [(0, 1, 4), (0, 2, 1), (1, 3, 1), (2, 3, 5), (2, 5, 10), (3, 4, 2), (4, 5, 3)]


def graph(spark, edges=EDGES, n=6):
    return Graph("small", spark.createDataFrame(edges, "src bigint, dst bigint, w bigint"), n)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_long_chains_are_followed_to_their_end(spark, tmp_path):
    from vertexlog.sources import graphs

    turns = [(c, t) for c in (0, 1) for t in range(1100)]
    spark.createDataFrame(turns, "conv_id bigint, turn bigint").write.parquet(str(tmp_path / "conversations.parquet"))
    g = graphs.dialog(spark, str(tmp_path))
    assert {(r["v"], r["label"]) for r in alg.components(g).collect()} == {(c * 1100 + t, c * 1100) for c, t in turns}
    chain = graph(spark, [(i, i + 1, 1) for i in range(12)], 13)
    assert rows(alg.sssp(chain, 0)) == [(i, i) for i in range(13)]
    for cut in (lambda: alg.sssp(chain, 0, max_steps=5), lambda: alg.components(g, max_steps=1)):
        with pytest.raises(ValueError):
            cut()


def test_stage_sizes_and_movement(spark):
    x = graph(spark)
    curve = metrics.reduction_curve(metrics.log_of(x.edges), 7, 2, 2)
    assert [r["records"] for r in curve.orderBy("phase").collect()] == [7, 6, 5, 5]
    step_by_step = metrics.reduction_curve(metrics.log_of(x.edges), 7, 2, 2, at_once=0)
    assert rows(step_by_step) == rows(curve)
    assert round(metrics.movement_ratio(curve).first()["ratio"], 3) == 0.762


@pytest.mark.parametrize("engine", sorted(ENGINES))
def test_search_by_every_engine(spark, engine):
    tree = alg.bfs(graph(spark), 0, engine=ENGINES[engine]())
    assert tree.sizes == [1, 2, 2, 1]
    assert rows(tree.rows()) == [(0, 0, 0), (1, 0, 1), (2, 0, 1), (3, 1, 2), (4, 3, 3), (5, 2, 2)]


@pytest.mark.parametrize("order", ["levels", "worklist"])
def test_search_in_one_task(spark, order):
    assert rows(local.bfs_local(graph(spark), 0, order)) == [(0, 0, 0), (1, 0, 1), (2, 0, 1), (3, 1, 2), (4, 3, 3), (5, 2, 2)]


def test_rank_round(spark):
    x = graph(spark)
    start = x.vertices().select("v", F.lit(1.0 / 6).alias("rank"))
    base = dict(rows(alg.rank_step(x, start)))
    assert [round(base[v], 7) for v in range(6)] == [0.025, 0.0958333, 0.0958333, 0.2375, 0.1666667, 0.2375]
    assert round(dict(rows(alg.rank_step(x, start, untouched="keep")))[0], 7) == 0.1666667


def test_fixed_rank_is_equal_in_all_forms(spark):
    x = graph(spark)
    first = rows(alg.rank_fixed(x, 3))
    for engine in ENGINES.values():
        assert rows(alg.rank_fixed(x, 3, engine=engine())) == first
    for mode in MODES:
        assert rows(alg.rank_fixed(x, 3, engine=Engine(mode, n=2, k=2))) == first
    assert rows(alg.rank_fixed(x, 3, lazy=True)) == first
    assert rows(local.rank_single(x, 3)) == first


def test_shortest_paths(spark):
    assert rows(alg.sssp(graph(spark), 0)) == [(0, 0), (1, 4), (2, 1), (3, 5), (4, 7), (5, 10)]


def test_betweenness_readings(spark):
    x = graph(spark)
    tree = alg.bfs(x, 0)
    assert rows(alg.bc_children(tree)) == [(0, 2), (1, 1), (2, 1), (3, 1)]
    assert rows(alg.bc_descendants(tree)) == [(0, 5), (1, 2), (2, 1), (3, 1)] == rows(local.bc_local(x, 0))
    exact = dict(rows(alg.bc_exact(x, 0, tree)))
    assert exact == {1: 1.0, 2: 2.0, 3: 1.0, 4: 0.0, 5: 0.0}
    assert sum(exact.values()) == sum((r["level"] - 1) for r in tree.rows().where("level > 0").collect())


def test_edge_cases_of_search(spark):
    empty = graph(spark, [], 3)
    assert rows(alg.bfs(empty, 0).rows()) == [(0, 0, 0)]
    assert rows(alg.bc_descendants(alg.bfs(empty, 0))) == []
    loop = graph(spark, [(0, 0, 1), (0, 1, 1), (0, 1, 2)], 2)
    assert rows(alg.bfs(loop, 0).rows()) == [(0, 0, 0), (1, 0, 1)]
    assert rows(alg.bfs(loop, 1).rows()) == [(1, 1, 0)]
    assert rows(alg.components(graph(spark, [(4, 3, 1), (1, 0, 1)], 5))) == [(0, 0), (1, 0), (3, 3), (4, 3)]
    assert rows(alg.rank_fixed(graph(spark, [], 1), 2)) == [(0, 150000000000)]


def test_long_chain_merges_its_visited_lists(spark):
    chain = graph(spark, [(i, i + 1, 1) for i in range(12)], 13)
    tree = alg.bfs(chain, 0, merge_after=3)
    assert tree.sizes == [1] * 13 and rows(alg.bc_descendants(tree, cut_every=4))[0] == (0, 12)


def test_budgets_are_refused_not_cut(spark):
    with pytest.raises(CapacityExceeded):
        alg.bfs(graph(spark), 0, engine=SemiExternal(memory=10))
    with pytest.raises(CapacityExceeded):
        local.arrays(graph(spark), most_edges=3)


def test_ordered_and_custom_reducers(spark):
    log = spark.createDataFrame([(1, 5, 0), (2, 7, 1), (1, 3, 2), (2, 1, 3), (1, 9, 4)], "dst bigint, val bigint, ord bigint")
    for mode in MODES:
        assert rows(fold(log, REDUCERS["first"], mode, 2, 2)) == [(1, 5), (2, 7)]
        assert rows(fold(log, REDUCERS["last"], mode, 2, 2)) == [(1, 9), (2, 1)]
        assert rows(fold(log, REDUCERS["count"], mode, 2, 2)) == [(1, 3), (2, 2)]
        assert rows(fold(log.limit(0), REDUCERS["sum"], mode, 2, 2)) == []
    assert rows(custom(log, lambda a, b: a * b)) == [(1, 135), (2, 7)]
    assert check_associative(spark, lambda a, b: a + b, [1, 2]).where("not ok").isEmpty()
    assert not check_associative(spark, lambda a, b: a - b, [1, 2]).where("not ok").isEmpty()


def test_merge_arithmetic():
    assert merge_phases(7, 2, 2) == 2 and merge_phases(5, 10, 2) == 0
    assert merge_plan(7, 2, 2) == [(0, 7, 4), (1, 4, 2), (2, 2, 1)]
    assert merge_tree(5) == [(1, 2), (2, 1), (3, 1)]
    for sizes in ([3], [1, 2, 3, 4, 5], [1] * 33):
        for pool in (1, 2, 3):
            done = merge_schedule(sizes, 4, pool)
            assert not done if len(sizes) == 1 else done[-1][2] == sum(sizes)


def test_costs():
    assert cost.fleet(17 * 10**12, 128 << 30)[0] == 124
    assert cost.project(4000, 500) == 2_000_000
    assert [cost.edge_scan_partitions(3_000_000_000, g << 30) for g in (16, 32, 64)] == [4, 2, 1] and cost.page_waste(4, 8192) == 2048
    fits = {(a, e): [g for gr, x, y, g, ok in cost.crossover() if (gr, x, y, ok) == ("web", a, e, True)] for a in cost.STATE for e in cost.ENGINES}
    assert [min(fits[a, "semi_external"]) for a in ("bfs", "rank", "betweenness")] == [48, 64, 96]
    assert all(min(fits[a, "sort_reduce"]) == 16 and not fits[a, "cached"] for a in cost.STATE)
    t = cost.tune(8 << 30, 32, 6e9)
    assert t.n * 16 * 2 * t.threads <= 8 << 30 and t.k >= 2


def test_ordinals_and_kronecker_agree(spark):
    df = spark.createDataFrame([(x,) for x in (5, 3, 3, 9, 1)], "a bigint")
    assert [r["ord"] for r in ordinal(df, "a").orderBy("a").collect()] == [0, 1, 2, 3, 4]
    assert rows(kron_edges(spark, 50, 6)) == sorted(kron_edge(i, 6) for i in range(50))


def test_kronecker_bits_are_compiled(spark):
    """A function over an array of bits is not: it took four times as long over 3.6 million edges."""
    assert "lambda" not in kron_edges(spark, 50, 6)._jdf.queryExecution().executedPlan().toString()


def test_tail_lookups_equal_joined_levels(spark):
    import random

    r = random.Random(4)
    edges = [(i, i + 1, 1) for i in range(40)] + [(r.randrange(41), r.randrange(41), 1) for _ in range(6)]
    x = graph(spark, edges, 42)
    joined = rows(alg.bfs(x, 0, tail_after=10_000).rows())
    assert rows(alg.bfs(x, 0, tail_after=1).rows()) == joined
    assert rows(alg.bfs(x, 0, tail_after=1, tail_rows=4).rows()) == joined
    assert rows(alg.bfs(x, 0, tail_after=1, max_levels=7).rows()) == [t for t in joined if t[2] <= 7]
