"""Single-task baselines in numpy: a sequential loop and an asynchronous worklist over edges of any number.

One task reads all edges in source order.  It holds a few numbers for each vertex; destinations lie in a file of its own
and are read in pieces, so that its memory grows with the vertices and with nothing else.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from vertexlog.operators.engines import CapacityExceeded
from vertexlog.sources.graphs import Graph

_FAR = np.iinfo(np.int64).max


def arrays(graph: Graph, most_edges: int = 1_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Edges as two arrays in source order; a graph that exceeds the bound is refused, not cut."""
    m = graph.edges.count()
    if m > most_edges:
        raise CapacityExceeded(f"{m} edges, {most_edges} allowed in one process")
    table = graph.edges.select("src", "dst").toArrow()
    src, dst = table["src"].to_numpy(), table["dst"].to_numpy()
    order = np.lexsort((dst, src))
    return src[order], dst[order]


class EdgeFile:
    """Out-edges of vertices 0..n-1: where each vertex's begin in memory, destinations in a file."""

    def __init__(self, batches: Iterator[pa.RecordBatch], n: int, path: str) -> None:
        """``batches`` of (src, dst) come sorted by source."""
        self.n, self.degree = n, np.zeros(n, np.int64)
        with open(path, "wb") as file:
            for batch in batches:
                if batch.num_rows:
                    src = batch.column(0).to_numpy()
                    self.degree[src[0] : src[-1] + 1] += np.bincount(src - src[0])
                    file.write(np.ascontiguousarray(batch.column(1).to_numpy()))
        self.first = np.concatenate([[0], np.cumsum(self.degree)])
        self.dst = np.memmap(path, np.int64, "r") if self.first[-1] else np.empty(0, np.int64)

    def out(self, v: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(place in ``v``, destination) of the edges that leave ``v``, up to ``most`` at a time; a hub's come in several pieces."""
        ends = np.cumsum(self.degree[v])
        begins = ends - self.degree[v]
        for low in range(0, int(ends[-1]) if len(v) else 0, most):
            high = min(low + most, int(ends[-1]))
            a, b = np.searchsorted(ends, low, "right"), np.searchsorted(begins, high, "left")
            start = np.maximum(begins[a:b], low)
            size = np.minimum(ends[a:b], high) - start
            shift = self.first[v[a:b]] - begins[a:b]
            yield np.repeat(np.arange(a, b), size), np.asarray(self.dst[np.repeat(shift, size) + np.arange(low, high)])


class Worklist:
    """Vertices that wait, first come first served, each at most once."""

    def __init__(self, n: int) -> None:
        self.ring, self.waiting, self.head, self.size = np.empty(n, np.int64), np.zeros(n, bool), 0, 0

    def put(self, v: np.ndarray) -> None:
        v = np.unique(v[~self.waiting[v]])
        self.waiting[v] = True
        self.ring[(self.head + self.size + np.arange(len(v))) % len(self.ring)] = v
        self.size += len(v)

    def take(self, most: int) -> np.ndarray:
        v = self.ring[(self.head + np.arange(min(most, self.size))) % len(self.ring)]
        self.head, self.size = (self.head + len(v)) % len(self.ring), self.size - len(v)
        self.waiting[v] = False
        return v


def _alone(graph: Graph, work: Callable[[EdgeFile], list[np.ndarray]], schema: str) -> DataFrame:
    """The columns that ``work`` makes of all edges, in one task."""
    n, names = graph.n, [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with tempfile.TemporaryDirectory(prefix="vertexlog-") as folder:
            columns = work(EdgeFile(batches, n, f"{folder}/dst"))
        for i in range(0, len(columns[0]), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(c[i : i + 100_000]) for c in columns], names=names)

    return graph.edges.select("src", "dst").coalesce(1).sortWithinPartitions("src").mapInArrow(run, schema)


def rank_single(graph: Graph, rounds: int, unit: int = 10**12) -> DataFrame:
    """Fixed-point rank by scattering every edge's share to its destination in turn."""
    share = unit // graph.n

    def work(edges: EdgeFile) -> list[np.ndarray]:
        every, val = np.arange(edges.n), np.full(edges.n, share, np.int64)
        for _ in range(rounds):
            total, part = np.zeros(edges.n, np.int64), val // np.maximum(edges.degree, 1)
            for at, dst in edges.out(every):
                np.add.at(total, dst, part[at])
            val = (15 * share + 85 * total) // 100
        return [every, val]

    return _alone(graph, work, "v bigint, rank_u bigint")


def rank_worklist(graph: Graph, damping: float = 0.85, tol: float = 1e-9, block: int = 1024) -> DataFrame:
    """Rank to its fixpoint without rounds: vertices pass on residuals as they come off a queue, ``block`` at a time.

    A residual waits until it reaches ``tol`` of the mean rank, so that errors are as small in a larger graph.
    """

    def work(edges: EdgeFile) -> list[np.ndarray]:
        every, n = np.arange(edges.n), edges.n
        rank, rest, queue = np.zeros(n), np.full(n, (1 - damping) / n), Worklist(n)
        queue.put(every)
        while queue.size:
            v = queue.take(block)
            r = rest[v]
            rest[v] = 0.0
            rank[v] += r
            part = damping * r / np.maximum(edges.degree[v], 1)
            for at, dst in edges.out(v):
                np.add.at(rest, dst, part[at])
                queue.put(dst[rest[dst] >= tol / n])
        return [every, rank + rest]

    return _alone(graph, work, "v bigint, rank double")


def search(edges: EdgeFile, root: int, order: str = "levels", block: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """(parent, level) arrays; ``levels`` ends a level before the next begins, ``worklist`` relaxes distances as they come.

    Parents are settled afterwards, in a pass over all edges.
    """
    level, queue = np.full(edges.n, _FAR), Worklist(edges.n)
    level[root] = 0
    queue.put(np.array([root]))
    while queue.size:
        v = queue.take(queue.size if order == "levels" else block)
        for at, dst in edges.out(v):
            new = level[v[at]] + 1
            nearer = new < level[dst]
            np.minimum.at(level, dst[nearer], new[nearer])
            queue.put(dst[nearer])
    parent, reached = np.full(edges.n, _FAR), np.flatnonzero(level != _FAR)
    for at, dst in edges.out(reached):
        src = reached[at]
        tight = level[src] + 1 == level[dst]
        np.minimum.at(parent, dst[tight], src[tight])
    parent[root] = root
    return parent, level


def bfs_local(graph: Graph, root: int, order: str = "levels") -> DataFrame:
    def work(edges: EdgeFile) -> list[np.ndarray]:
        parent, level = search(edges, root, order)
        reached = np.flatnonzero(level != _FAR)
        return [reached, parent[reached], level[reached].astype(np.int32)]

    return _alone(graph, work, "v bigint, parent bigint, level int")


def bc_local(graph: Graph, root: int, order: str = "levels") -> DataFrame:
    """Tree paths through each vertex, from the deepest level up."""

    def work(edges: EdgeFile) -> list[np.ndarray]:
        parent, level = search(edges, root, order)
        reached = np.flatnonzero(level != _FAR)
        reached = reached[np.argsort(level[reached], kind="stable")]
        starts = np.flatnonzero(np.diff(level[reached])) + 1  # where the levels below the root begin
        score = np.zeros(edges.n, np.int64)
        for low, high in zip(starts[::-1], [*starts, len(reached)][:0:-1], strict=True):
            v = reached[low:high]
            np.add.at(score, parent[v], 1 + score[v])
        own = np.sort(reached[score[reached] > 0])
        return [own, score[own]]

    return _alone(graph, work, "v bigint, score bigint")
