"""Vertex programs: what a user states, and the loop that runs it."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexlog.operators.engines import Engine
from vertexlog.operators.updatelog import UpdateLog
from vertexlog.sources.graphs import Graph
from vertexlog.sources.scratch import Scratch


@dataclass(frozen=True)
class EdgeContext:
    """Columns an edge function may use: the source's value, the edge's weight, source id, out-degree, superstep."""

    val: Column = field(default_factory=lambda: F.col("val"))
    weight: Column = field(default_factory=lambda: F.col("w"))
    src: Column = field(default_factory=lambda: F.col("src"))
    out_degree: Column = field(default_factory=lambda: F.col("degree"))
    step: int = 0


@dataclass(frozen=True)
class VertexProgram:
    """Edge function, reducer, finaliser and activity test over columns.

    ``finalize(old, folded)`` gives the new value (``old`` is null for a vertex never touched);
    ``is_active(old, new)`` says whether the vertex pushes in the next round.
    """

    name: str
    edge: Callable[[EdgeContext], Column]
    reducer: str
    finalize: Callable[[Column, Column], Column]
    is_active: Callable[[Column, Column], Column]
    needs_degree: bool = False


def semiring(name: str, mul: Callable[[Column, Column], Column], add: str) -> VertexProgram:
    """The algebraic view: an edge multiplies its source's value by its weight, destinations add."""
    better = {"min": F.least, "max": F.greatest}.get(add)
    finalize = (lambda old, new: better(F.coalesce(old, new), new)) if better else (lambda old, new: new)
    return VertexProgram(name, lambda c: mul(c.val, c.weight), add, finalize, lambda old, new: old.isNull() | (old != new))


@dataclass
class RunResult:
    values: DataFrame
    trace: list[tuple[int, int, int]]
    log: UpdateLog

    def steps(self) -> int:
        return len(self.trace)

    def finished(self) -> bool:
        """Whether no vertex was active any more when the run ended."""
        return not self.trace or self.trace[-1][2] == 0


def commit(updates: DataFrame, current: DataFrame, program: VertexProgram, sweep: str = "touched") -> DataFrame:
    """(v, val, active): new values of the vertices with updates, or of all vertices for ``sweep="all"``."""
    u = updates.select(F.col("dst").alias("v"), F.col("val").alias("folded"))
    joined = u.join(current.select("v", F.col("val").alias("old")), "v", "left" if sweep == "touched" else "full")
    new = F.when(F.col("folded").isNull(), F.col("old")).otherwise(program.finalize(F.col("old"), F.col("folded")))
    on = F.col("folded").isNotNull() & F.coalesce(program.is_active(F.col("old"), F.col("new")), F.lit(False))
    return joined.withColumn("new", new).select("v", F.col("new").alias("val"), on.alias("active"))


def run(graph: Graph, program: VertexProgram, start: DataFrame, *, max_steps: int | None = None, engine: Engine | None = None, max_lists: int = 8) -> RunResult:
    """Supersteps until no vertex is active, or ``max_steps`` of them: see ``RunResult.finished``.

    Where few vertices are active, a round writes the folded updates and reads the old values of just these vertices
    from the ranges they lie in; else it reads all lists.  It appends what changed; the number of newly active vertices comes from the written files.  Lists are compacted
    when there are more than ``max_lists``, so plans stay short however many rounds there are.
    """
    engine = engine or Engine()
    edges = engine.prepare(graph)
    if program.needs_degree:
        edges = edges.join(graph.degrees().withColumnRenamed("v", "src"), "src")
    log, folded = UpdateLog(graph.edges.sparkSession, program.name, graph.width), Scratch(graph.edges.sparkSession, "updates")
    active, trace = log.append(0, start.select("v", "val")), []
    size = active.count()
    for step in count(1) if max_steps is None else range(1, max_steps + 1):
        if not size:
            break
        updates = engine.round(active, edges, program.edge(EdgeContext(step=step)), program.reducer, size)
        if graph.width and 4 * size <= graph.n:
            updates = folded.keep(updates)
            current = log.resolve(updates.select(F.col("dst").alias("v")))
        else:
            current = log.resolve()
        done = commit(updates, current, program).where("active").select("v", "val")
        active = log.append(step, done)
        trace.append((step, size, now := log.size(step)))
        size = now
        log.compact_if(max_lists) if len(log.lists) > max_lists else None
    engine.finish()
    folded.drop()
    return RunResult(log.resolve().select("v", "val"), trace, log)


def keep(df: DataFrame, tag: str) -> DataFrame:
    return Scratch(df.sparkSession, tag).keep(df)
