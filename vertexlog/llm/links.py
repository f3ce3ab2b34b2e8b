"""Connected components of a distributed link table, and spanning forests inside one task.

``components`` contracts links to stars with min-aggregates and equi joins only: no round gathers the neighbours
of a node, so a hub with many links is a partial aggregate and a splittable join, never one task's list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vertexlog.llm.common import Scratch

LINKS = "u bigint, v bigint"


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Star links (node, smallest node of its component) with the same components as the links a-b."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while len(x):
        low = np.minimum(label[x], label[y])
        before = label.copy()
        np.minimum.at(label, label[x], low)
        np.minimum.at(label, label[y], low)
        while not np.array_equal(label, shorter := label[label]):
            label = shorter
        if np.array_equal(label, before):
            break
    far = np.flatnonzero(label != np.arange(len(nodes)))
    return nodes[far], nodes[label[far]]


def contract(batches: Iterator[pa.RecordBatch], limit: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """Replace the links of a task by a forest, in chunks of at most ``limit`` links at a time."""
    u, v, held = [], [], 0
    for batch in batches:
        u.append(batch.column(0).to_numpy(zero_copy_only=False))
        v.append(batch.column(1).to_numpy(zero_copy_only=False))
        held += batch.num_rows
        if held > limit:
            a, b = forest(np.concatenate(u), np.concatenate(v))
            if len(a) > limit // 2:
                yield from _as_batches(a, b)
                u, v, held = [], [], 0
            else:
                u, v, held = [a], [b], len(a)
    if held:
        yield from _as_batches(*forest(np.concatenate(u), np.concatenate(v)))


def _as_batches(a: np.ndarray, b: np.ndarray, rows: int = 50_000) -> Iterator[pa.RecordBatch]:
    for i in range(0, len(a), rows):
        yield pa.RecordBatch.from_arrays([pa.array(a[i : i + rows], pa.int64()), pa.array(b[i : i + rows], pa.int64())], names=["u", "v"])


def _both(links: DataFrame) -> DataFrame:
    return links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _with_least(links: DataFrame, salts: int) -> DataFrame:
    """links with ``m``, the smallest v of each u.

    A hub is a key with many rows, so links are dealt out by (u, salt of v).  The least of each such part comes first,
    then the least of all parts, which goes back to those parts only that occur: rows of a hub meet by their parts.
    """
    dealt = links.withColumn("s", F.pmod(F.xxhash64("v"), F.lit(salts)).cast("int"))
    part = dealt.groupBy("u", "s").agg(F.min("v").alias("m"))
    least = part.groupBy("u").agg(F.min("m").alias("m"), F.collect_list("s").alias("s")).select("u", F.explode("s").alias("s"), "m")
    return dealt.join(least, ["u", "s"]).select("u", "v", "m")


def _large_star(links: DataFrame, salts: int) -> DataFrame:
    return _with_least(_both(links), salts).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))


def _small_star(links: DataFrame, salts: int) -> DataFrame:
    met = _with_least(links, salts)
    moved = met.select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
    return moved.distinct()


def components(links: DataFrame, salts: int = 256) -> DataFrame:
    """(u, v) -> (u, root): every node that is not the smallest of its component, with that smallest node.

    Links may come in any direction, repeat, or join a node with itself.  An empty table gives an empty one.  Rounds
    go on until nothing changes; their number grows with the logarithm of the longest chain.
    """
    scratch = Scratch(links.sparkSession, "components")
    down = links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    now = scratch.keep(down.mapInArrow(contract, LINKS).distinct())
    mark = None
    while True:
        now = scratch.keep(_small_star(scratch.keep(_large_star(now, salts)), salts))
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        scratch.forget(1)
        if mark == seen or not seen[0]:
            return now.select("u", F.col("v").alias("root"))
        mark = seen
