"""The update log and its folding: in place, sorted first, interleaved with merging, or fused into one exchange.

A log has rows (dst, val) and, where the reducer depends on order, ``ord``: the place of the record when records
are emitted by rising source.
"""

from __future__ import annotations

import math
from collections import deque
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from vertexlog.functions.reducers import Reducer
from vertexlog.sources.scratch import Scratch

MODES = ("fused", "in_place", "sort_first", "interleaved")


def emit_log(active: DataFrame, edges: DataFrame, message: Callable[[], Column] | Column, *, carry: tuple[str, ...] = (), broadcast_active: bool = False) -> DataFrame:
    """One record (dst, val) for every edge that leaves an active vertex.

    ``active`` has (v, val, ...); ``message`` is a column over these and the edge's columns.  A small active list is
    broadcast, so that the edges are neither shuffled nor sorted; else the join is by source.
    """
    left = F.broadcast(active) if broadcast_active else active
    joined = edges.join(left, edges["src"] == left["v"])
    made = message() if callable(message) else message
    return joined.select("dst", made.alias("val"), *carry)


def fold(log: DataFrame, reducer: Reducer, mode: str = "fused", n: int = 4096, k: int = 16) -> DataFrame:
    """(dst, val): one record for each destination of the log.

    ``fused`` folds in map tasks, then after one exchange.  ``in_place`` sends every record to the task that holds its
    destination, which applies it to that vertex's value, one record after the other.  ``sort_first`` sorts the whole
    log into files before anything is folded.  ``interleaved`` folds blocks of n records as they are emitted and merges
    k blocks at a time, folding again in each merge.
    """
    order = F.col("ord") if "ord" in log.columns else F.lit(0)
    lifted = reducer.lift(F.col("val"), order).alias("val")
    if reducer.ordered and mode != "fused" and "ord" not in log.columns:
        raise ValueError(f"{reducer.name} needs the places of records")
    if mode == "fused":
        return log.groupBy("dst").agg(lifted)
    if mode == "in_place":
        return apply_in_place(log, reducer)
    if mode == "sort_first":
        return Scratch(log.sparkSession, "sorted").keep(sorted_log(log)).groupBy("dst").agg(lifted)
    if mode == "interleaved":
        now, blocks = first_blocks(log, n, reducer)
        while blocks > 1:
            now = merge_reduce(now, k, reducer)
            blocks = math.ceil(blocks / k)
        return now.select("dst", "val")
    raise ValueError(mode)


def sorted_log(log: DataFrame) -> DataFrame:
    """The log in order of destination; a destination with very many records is cut by their places or values."""
    keys = ["dst", "ord" if "ord" in log.columns else "val"]
    return log.repartitionByRange(*keys).sortWithinPartitions(*keys)


def first_blocks(log: DataFrame, n: int, reducer: Reducer) -> tuple[DataFrame, int]:
    """The log folded in blocks of n records in the order of emission, and the number of blocks.

    Records are numbered where they are emitted: a task's blocks are its own runs of n records, so that nothing is
    sorted or moved before it is folded.  Blocks of all tasks are then numbered through.
    """
    if "ord" in log.columns:
        return block_reduce(log, n, reducer), math.ceil(((log.agg(F.max("ord")).first()[0] or 0) + 1) / n)
    place = F.monotonically_increasing_id()
    numbered = log.withColumn("task", F.shiftright(place, 33)).withColumn("run", F.expr(f"{(1 << 33) - 1} & monotonically_increasing_id()")).withColumn("run", F.expr(f"run div {n}"))
    folded = Scratch(log.sparkSession, "blocks").keep(numbered.groupBy("task", "run", "dst").agg(reducer.lift(F.col("val"), F.lit(0)).alias("val")))
    runs = sorted((r["task"], r["n"]) for r in folded.groupBy("task").agg((F.max("run") + 1).alias("n")).collect())  # one row a task
    first, rows = 0, []
    for task, count in runs:
        rows.append((task, first))
        first += count
    starts = log.sparkSession.createDataFrame(rows, "task bigint, first bigint")
    dense = folded.join(F.broadcast(starts), "task").select((F.col("first") + F.col("run")).alias("block"), "dst", "val", F.lit(0).cast("bigint").alias("ord"))
    return dense, first


def apply_in_place(log: DataFrame, reducer: Reducer) -> DataFrame:
    """Every record applied to its vertex's value by itself; a task holds the values of its vertices."""
    if reducer.pair is None:
        raise ValueError(f"{reducer.name} has no function of two values")
    out = log.groupBy("dst").agg(reducer.lift(F.col("val"), F.lit(0)).alias("val")).schema
    pair, unit = reducer.pair, reducer.unit
    sent = log.where("val is not null").repartition("dst")
    if "ord" in log.columns:
        sent = sent.sortWithinPartitions("ord")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values: dict = {}
        for batch in batches:
            for v, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                values[v] = pair(values[v], unit(x)) if v in values else unit(x)
        kinds = to_arrow_schema(out)
        keys = list(values)
        for i in range(0, len(keys), 100_000):
            part = keys[i : i + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part, kinds.field(0).type), pa.array([values[v] for v in part], kinds.field(1).type)], names=["dst", "val"])

    return sent.select("dst", "val").mapInArrow(run, out)


def block_reduce(log: DataFrame, n: int, reducer: Reducer) -> DataFrame:
    """Phase one: the log in blocks of n records, each folded: (block, dst, val, ord)."""
    block = F.expr(f"ord div {n}").alias("block")
    first = F.max("ord") if reducer.name in ("last", "max_by") else F.min("ord")
    return log.groupBy(block, "dst").agg(reducer.lift(F.col("val"), F.col("ord")).alias("val"), first.alias("ord"))


def merge_reduce(blocks: DataFrame, k: int, reducer: Reducer) -> DataFrame:
    """Phase two, one step: k neighbouring blocks become one, equal destinations folded."""
    block = F.expr(f"block div {k}").alias("block")
    first = F.max("ord") if reducer.name in ("last", "max_by") else F.min("ord")
    return blocks.groupBy(block, "dst").agg(reducer.again()(F.col("val"), F.col("ord")).alias("val"), first.alias("ord"))


def partition_log(log: DataFrame, width: int, parts: int) -> DataFrame:
    """The log dealt out over destination ranges of equal width; later folds by (part, dst) need no exchange."""
    ranged = log.withColumn("part", F.expr(f"dst div {width}").cast("int"))
    return ranged.repartitionById(parts, F.pmod("part", F.lit(parts)).cast("int")) if hasattr(ranged, "repartitionById") else ranged.repartition(parts, "part")


def merge_phases(m: int, n: int, k: int) -> int:
    """How many merge steps a log of m records needs."""
    blocks, steps = -(-m // n), 0
    while blocks > 1:
        blocks, steps = -(-blocks // k), steps + 1
    return steps


def merge_plan(m: int, n: int, k: int) -> list[tuple[int, int, int]]:
    """(phase, blocks in, blocks out), phase 0 being the block folds."""
    blocks, out = -(-m // n), [(0, m, -(-m // n))]
    while blocks > 1:
        out.append((len(out), blocks, -(-blocks // k)))
        blocks = -(-blocks // k)
    return out


def merge_tree(k: int) -> list[tuple[int, int]]:
    """(level, two-way mergers) of the tree inside one k-way merger."""
    out, streams = [], k
    while streams > 1:
        out.append((len(out) + 1, streams // 2))
        streams = -(-streams // 2)
    return out


def merge_schedule(sizes: list[int], k: int, pool: int = 1) -> list[tuple[int, int, int]]:
    """First-in first-out merging of block files: (merge, files taken, size written) until one file is left.

    Up to ``pool`` merges run at a time; their results queue in the order in which they started.
    """
    queue, running, out = deque(sizes), deque(), []
    while len(queue) + len(running) > 1:
        while len(queue) > 1 and len(running) < pool:
            taken = [queue.popleft() for _ in range(min(k, len(queue)))]
            out.append((len(out) + 1, len(taken), sum(taken)))
            running.append(sum(taken))
        if running:
            queue.append(running.popleft())
    return out
