"""Ways to carry out one round (active list x edges -> folded updates); all give the same values.

The differences are what they keep in memory, what they read and when they fold: see ``Engine`` and its kinds.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexlog.functions.reducers import REDUCERS
from vertexlog.operators.sortreduce import emit_log, fold
from vertexlog.plans.cost import edge_scan_partitions
from vertexlog.sources.graphs import Graph
from vertexlog.sources.scratch import Scratch


class CapacityExceeded(RuntimeError):
    """The state that an engine keeps in memory does not fit its budget."""


class Engine:
    """Sort-reduce: edges of active ranges only, partial folds in the tasks that read them, one exchange, final folds."""

    name = "sort_reduce"
    value_bytes = 16
    selective = True

    def __init__(self, mode: str = "fused", n: int = 4096, k: int = 16, broadcast_rows: int = 10_000) -> None:
        self.mode, self.n, self.k, self.broadcast_rows = mode, n, k, broadcast_rows
        self.vertices, self.width = 0, None
        self.opened: list[list[int] | None] = []  # the source ranges read in each round, or None for all

    def prepare(self, graph: Graph) -> DataFrame:
        self.vertices, self.width = graph.n, graph.width
        return graph.edges

    def finish(self) -> None:
        """Give back what the engine holds, after the last round."""

    def ranges(self, active: DataFrame, size: int | None) -> list[int] | None:
        """Ranges of sources that a frontier needs; None if it is large or edges are not laid out."""
        if not self.selective or self.width is None or size is None or 4 * size > self.vertices:
            return None
        return sorted(r[0] for r in active.select(F.expr(f"v div {self.width}")).distinct().collect())  # at most 4,096

    def open(self, edges: DataFrame, ranges: list[int] | None) -> DataFrame:
        self.opened.append(ranges)
        return edges if ranges is None else edges.where(F.col("src_part").isin(ranges))

    def round(self, active: DataFrame, edges: DataFrame, message: Column, reducer: str, size: int | None = None) -> DataFrame:
        """(dst, val) after one round; ``size`` is the number of active vertices where it is known."""
        read = self.open(edges, self.ranges(active, size))
        return self.apply(active, read, message, reducer, size)

    def apply(self, active: DataFrame, edges: DataFrame, message: Column, reducer: str, size: int | None) -> DataFrame:
        small = size is not None and size <= self.broadcast_rows
        return fold(emit_log(active, edges, message, broadcast_active=small), REDUCERS[reducer], self.mode, self.n, self.k)


class SemiExternal(Engine):
    """All vertex values in every worker's memory, edges read selectively; refuses what does not fit."""

    name = "semi_external"

    def __init__(self, memory: int = 1 << 30, value_bytes: int = 16) -> None:
        super().__init__()
        self.memory, self.value_bytes = memory, value_bytes

    def prepare(self, graph: Graph) -> DataFrame:
        need = graph.n * self.value_bytes
        if need > self.memory:
            raise CapacityExceeded(f"{need} bytes of vertex values, {self.memory} allowed")
        return super().prepare(graph)

    def apply(self, active, edges, message, reducer, size):
        """Values of all vertices, active or not, travel to every worker; their edges find them by a lookup there."""
        every = edges.sparkSession.range(self.vertices).select(F.col("id").alias("v")).join(active.withColumn("__on", F.lit(True)), "v", "left")
        log = edges.join(F.broadcast(every), edges["src"] == every["v"]).where("__on").select("dst", message.alias("val"))
        return fold(log, REDUCERS[reducer])


class EdgeScan(Engine):
    """Every edge is read each round, whether its source is active or not; updates are logged by partition.

    Vertices are cut into as many partitions as it takes until one partition's values fit the memory; the log goes to
    files by partition first and each file is folded by itself.
    """

    name = "edge_scan"
    selective = False

    def __init__(self, memory: int = 1 << 30, value_bytes: int = 16) -> None:
        super().__init__()
        self.memory, self.value_bytes, self.partitions = memory, value_bytes, 1

    def prepare(self, graph: Graph) -> DataFrame:
        self.partitions = edge_scan_partitions(graph.n, self.memory, self.value_bytes)
        return super().prepare(graph)

    def apply(self, active, edges, message, reducer, size):
        flagged = active.withColumn("__on", F.lit(True))
        seen = edges.join(flagged, edges["src"] == flagged["v"], "left")
        part = F.expr(f"dst div {max(1, -(-self.vertices // self.partitions))}")
        log = seen.select("dst", message.alias("val"), "__on", part.alias("part")).where("__on").drop("__on")
        path = f"{Scratch(edges.sparkSession, 'scan').root}/log"
        log.write.partitionBy("part").parquet(path)
        written = edges.sparkSession.read.schema(log.schema).parquet(path)
        folds = [fold(written.where(F.col("part") == i).select("dst", "val"), REDUCERS[reducer]) for i in range(self.partitions)]
        return reduce(DataFrame.unionByName, folds)


class MultiPass(Engine):
    """One pass over the edges for each interval of destinations; only that interval's values are held."""

    name = "multi_pass"
    selective = False

    def __init__(self, intervals: int = 4) -> None:
        super().__init__()
        self.intervals = intervals

    def apply(self, active, edges, message, reducer, size):
        width = max(1, -(-self.vertices // self.intervals))
        passes = [
            fold(emit_log(active, edges.where((F.col("dst") >= i * width) & (F.col("dst") < (i + 1) * width)), message), REDUCERS[reducer])
            for i in range(self.intervals)
        ]
        return reduce(DataFrame.unionByName, passes)


class Cached(Engine):
    """Edges and values stay in the cluster's memory, partitioned by source; refuses what does not fit."""

    name = "cached"
    selective = False

    def __init__(self, memory: int = 4 << 30, edge_bytes: int = 24) -> None:
        super().__init__()
        self.memory, self.edge_bytes, self.held = memory, edge_bytes, None

    def prepare(self, graph: Graph) -> DataFrame:
        need = graph.edges.count() * self.edge_bytes + graph.n * self.value_bytes
        if need > self.memory:
            raise CapacityExceeded(f"{need} bytes of graph, {self.memory} allowed")
        self.held = super().prepare(graph).repartition("src").persist(StorageLevel.MEMORY_ONLY)
        return self.held

    def finish(self) -> None:
        if self.held is not None:
            self.held.unpersist()


class Dataflow(Engine):
    """A join and a grouping without layout, lists or hints: every message travels to its destination unfolded."""

    name = "dataflow"
    selective = False

    def apply(self, active, edges, message, reducer, size):
        return fold(emit_log(active.hint("merge"), edges, message).repartition("dst"), REDUCERS[reducer])


ENGINES: dict[str, Callable[[], Engine]] = {e.name: e for e in (Engine, SemiExternal, EdgeScan, MultiPass, Cached, Dataflow)}
