"""Single-task baselines on more edges than one process was allowed to hold, and their reading in pieces."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from vertexlog.operators import local
from vertexlog.sources.graphs import Graph

N, TIMES = 1000, 1200


def ring(spark):
    """1.2 million edges: every vertex to the next one, 1,200 times."""
    return Graph("ring", spark.range(N * TIMES).select((F.col("id") % N).alias("src"), ((F.col("id") + 1) % N).alias("dst")), N)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_rank_of_more_than_a_million_edges(spark):
    share = 10**12 // N
    assert rows(local.rank_single(ring(spark), 1)) == [(v, (15 * share + 85 * (share // TIMES * TIMES)) // 100) for v in range(N)]
    assert all(abs(rank - 1 / N) < 1e-9 for _, rank in rows(local.rank_worklist(ring(spark))))


@pytest.mark.parametrize("order", ["levels", "worklist"])
def test_search_of_more_than_a_million_edges(spark, order):
    assert rows(local.bfs_local(ring(spark), 0, order)) == [(v, max(v - 1, 0), v) for v in range(N)]
    assert rows(local.bc_local(ring(spark), 0, order)) == [(v, N - 1 - v) for v in range(N - 1)]


def test_graph_without_edges(spark):
    x = Graph("none", spark.createDataFrame([], "src bigint, dst bigint"), 3)
    assert [v for v, _ in rows(local.rank_single(x, 1))] == [0, 1, 2]
    assert rows(local.bfs_local(x, 1)) == [(1, 1, 0)] and rows(local.bc_local(x, 1)) == []


@pytest.mark.parametrize("most", [1, 2, 3, 7])
def test_edges_come_in_pieces(tmp_path, most):
    edges = [(0, 5), (2, 1), (2, 2), (2, 3), (2, 4), (5, 0), (5, 9)]
    batches = [pa.record_batch([pa.array([s for s, _ in part]), pa.array([d for _, d in part])], names=["src", "dst"]) for part in (edges[:3], edges[3:])]
    file = local.EdgeFile(iter(batches), 10, str(tmp_path / "dst"))
    wanted = np.array([5, 1, 2, 0])
    pieces = [(at, dst) for at, dst in file.out(wanted, most)]
    assert all(len(dst) <= most for _, dst in pieces)
    assert [(int(wanted[a]), int(d)) for at, dst in pieces for a, d in zip(at, dst, strict=True)] == [e for v in wanted for e in edges if e[0] == v]
