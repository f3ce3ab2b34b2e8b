"""The driver's entry points, and a sample of queries against DuckDB on the smallest tables."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry

SAMPLE = ["pagerank_step", "bfs_copurchase", "bc_descendants_trade", "vs_union", "degree_hist", "superstep_interleaved", "baseline_edge_scan_bfs", "asof_edges", "stream_chain_edges", "pagerank_unconverged_active", "long_tail_projection", "scan_efficiency", "expand_seek", "log_resolve_some", "superstep_in_place", "superstep_sort_first", "reduce_custom_ordered", "vs_dense", "levels_pivot", "encoding_choice", "import_text", "crossover_grid", "edge_scan_partitions", "sssp_trade", "sink_bucketed", "approx_reach_within", "tuning_grid", "merge_schedule"]


def test_flagship_has_rows(spark):
    out = entry.entry(spark)
    assert out.columns == ["v", "rank_u"] and out.count() == 20


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    for path in glob.glob(f"{tiny}/*.parquet"):
        con.execute(f"create view {os.path.basename(path)[:-8]} as select * from '{path}'")
    return con


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, tiny, duck, name):
    got = entry.queries()[name](spark, tiny)
    columns = sorted(got.columns)
    answer = duck.execute(entry.oracle_sql()[name])
    names = [d[0] for d in answer.description]
    assert sorted(names) == columns
    nulls_last = lambda row: [(x is None, x) for x in row]
    expected = sorted((tuple(r[names.index(c)] for c in columns) for r in answer.fetchall()), key=nulls_last)
    assert sorted((tuple(r) for r in got.select(columns).collect()), key=nulls_last) == expected


def test_calls_in_sql_become_views(spark, tiny):
    from vertexlog.operators.sqlsurface import sql

    out = sql(spark, tiny, "select count(*) as n from bfs('g_copurchase', 0) b join rank('g_copurchase', 1) r on b.v = r.v")
    assert out.first()["n"] == 200
