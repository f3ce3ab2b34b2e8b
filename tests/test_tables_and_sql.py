"""Queries whose rows once parted from their SQL at another size than that of the tests."""

import datetime
import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry
from vertexlog.plans import metrics
from vertexlog.streaming.events import as_of


def by_sql(folder, name):
    """(columns, sorted rows) that the SQL of a query gives on the tables of a folder."""
    con = duckdb.connect()
    for path in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"create view {os.path.basename(path)[:-8]} as select * from '{path}{'/*.parquet' if os.path.isdir(path) else ''}'")
    answer = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in answer.description]
    return sorted(names), sorted(tuple(r[names.index(c)] for c in sorted(names)) for r in answer.fetchall())


def by_spark(spark, folder, name):
    got = entry.queries()[name](spark, str(folder))
    return sorted(got.columns), sorted(tuple(r[c] for c in sorted(got.columns)) for r in got.collect())


@pytest.mark.parametrize("name", ["edges_kron", "kron_source", "kron_udtf", "limit_offset", "pagerank_step_kron"])
def test_kronecker_scale_is_that_of_the_sql(spark, tiny, name):
    assert by_spark(spark, tiny, name) == by_sql(tiny, name)


def test_a_purchase_at_the_time_of_a_view_is_not_before_it(spark, tmp_path):
    at = lambda *t: datetime.datetime(2024, 1, *t)
    events = [(1, at(1, 8), "purchase"), (2, at(1, 9), "purchase"), (3, at(1, 9), "view"), (4, at(2, 9), "view"), (0, at(2, 9), "purchase"), (5, None, "purchase"), (6, None, "view"), (7, at(2, 10), "view"), (8, at(1, 7), "view")]
    spark.createDataFrame(events, "event_id bigint, ts timestamp, event_type string").coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    assert by_spark(spark, tmp_path, "asof_edges") == by_sql(tmp_path, "asof_edges")
    tied = [(1, at(1, 8), "purchase"), (3, at(1, 8), "purchase"), (2, at(1, 8), "purchase"), (4, at(1, 9), "view")]
    assert [tuple(r) for r in as_of(spark.createDataFrame(tied, "event_id bigint, ts timestamp, event_type string")).collect()] == [(3, 4)]


@pytest.mark.parametrize("name", ["assoc_check", "crossover_grid", "edge_scan_partitions", "fleet_cost", "memory_need", "merge_tree", "tuning_grid"])
def test_costs_are_those_of_the_given_tables(spark, tiny, name):
    made = []
    use = metrics.stage_totals(spark, lambda: made.append(by_spark(spark, tiny, name)))
    assert use["rows_read"] >= 6000 and made[0] == by_sql(tiny, name) and made[0][1]


def test_betweenness_rounds_halves_as_the_sql(spark, tmp_path):
    """The first page below the root scores 1 + 1/640 = 1.0015625: once for a target of its own, once for a share of another."""
    link = lambda *targets: "".join(f'<a href="/{t}">' for t in targets)
    pages = [(0, link("top")), (1, link("top", "shared", "own")), *((i, link("top", "shared")) for i in range(2, 641))]
    spark.createDataFrame(pages, "page_id bigint, html string").coalesce(1).write.parquet(str(tmp_path / "pages.parquet"))
    assert by_spark(spark, tmp_path, "bc_exact_weblink") == by_sql(tmp_path, "bc_exact_weblink")
