"""Sharding on a consistent-hash ring with virtual nodes and bounded loads.

The ring has ``2 ** slice_bits`` slices; each shard owns ``replicas`` points of it, and a slice belongs to the
first point clockwise.  Rows hash to slices by their id.  Rows come to the ring in slice order; when a shard is
full, the rows that would go there continue clockwise to the next point whose shard has room.  With
``slack = 0`` capacities add up to the number of rows, so counts differ by one at most; a larger slack moves
fewer rows when a shard is added.

Plan: ids, sizes and checksums go into a narrow table of distinct rows and how often each occurs.  The driver sees one
count per slice (a fixed number) and returns at most ``slices + shards`` segments, which are broadcast.  A row's rank
in its slice is its place by (id, size, checksum), so results depend neither on files nor on tasks; a row that a third
of the table repeats is one row with a count until it is unfolded, in runs of ``run`` ranks.

Defined results: null text has no bytes; null ids share a slice and come first in it; repeated rows are placed one by
one, side by side; an empty table gives an empty one.
"""

from __future__ import annotations

from bisect import bisect_left

import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vertexlog.llm.common import Scratch

SEGMENTS = "slice int, low bigint, high bigint, shard int, base bigint"


def ring(shards: int, replicas: int, slice_bits: int) -> tuple[list[int], list[int]]:
    """Places of the points in clockwise order and the shard of each."""
    points = sorted((xxhash.xxh64_intdigest(f"{s}/{r}", 42) >> (64 - slice_bits), s) for s in range(shards) for r in range(replicas))
    return [p for p, _ in points], [s for _, s in points]


def capacities(rows: int, shards: int, slack: float) -> list[int]:
    if slack:
        return [int(-(-rows * (1 + slack) // shards))] * shards
    return [rows // shards + (s < rows % shards) for s in range(shards)]


def place(counts: dict[int, int], shards: int, replicas: int = 128, slice_bits: int = 14, slack: float = 0.0) -> list[tuple[int, int, int, int, int]]:
    """Segments (slice, first rank, end rank, shard, first slot) for the number of rows in each slice."""
    at, owner = ring(shards, replicas, slice_bits)
    room = capacities(sum(counts.values()), shards, slack)
    points: list[list[int]] = [[] for _ in range(shards)]
    for i, s in enumerate(owner):
        points[s].append(i)
    ahead = list(range(len(at)))  # the next point with room, itself included

    def open_point(i: int) -> int:
        path = []
        while ahead[i] != i:
            path.append(i)
            i = ahead[i]
        for p in path:
            ahead[p] = i
        return i

    def close(shard: int) -> None:
        if any(r > 0 for r in room):
            for p in points[shard]:
                n = p
                while room[owner[n]] == 0:
                    n = (n + 1) % len(at)
                ahead[p] = n

    used, out = [0] * shards, []
    for s in range(shards):
        if not room[s]:
            close(s)
    for piece in sorted(counts):
        low, left = 0, counts[piece]
        while left:
            shard = owner[open_point(bisect_left(at, piece) % len(at))]
            take = min(left, room[shard])
            out.append((piece, low, low + take, shard, used[shard]))
            used[shard] += take
            room[shard] -= take
            low, left = low + take, left - take
            if not room[shard]:
                close(shard)
    return out


def shard_rows(docs: DataFrame, *, shards: int = 40, id_col: str = "doc_id", text_col: str = "text", overhead: int = 16, replicas: int = 128, slice_bits: int = 14, slack: float = 0.0, run: int = 10_000) -> DataFrame:
    """(id, size, text_crc32, shard, slot) for every row."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col), F.lit(""))
    each = docs.select(
        F.col(id_col).alias("__id"),
        (F.octet_length(text) + overhead).cast("bigint").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.shiftrightunsigned(F.xxhash64(F.col(id_col)), 64 - slice_bits).cast("int").alias("slice"),
    )
    rows = Scratch(spark, "shards").keep(each.groupBy(each.columns).agg(F.count("*").alias("n")))
    per_slice = {r["slice"]: r["n"] for r in rows.groupBy("slice").agg(F.sum("n").alias("n")).toLocalIterator()}
    segments = spark.createDataFrame(place(per_slice, shards, replicas, slice_bits, slack), SEGMENTS)
    after = F.sum("n").over(Window.partitionBy("slice").orderBy("__id", "size", "text_crc32"))
    parts = rows.withColumn("end", after).withColumn("first", F.col("end") - F.col("n"))
    cut = parts.join(F.broadcast(segments), "slice").where("first < high and end > low")
    ranks = cut.withColumn("a", F.greatest("first", "low")).withColumn("b", F.least("end", "high") - 1)
    runs = ranks.withColumn("a", F.explode(F.sequence("a", "b", F.lit(run).cast("bigint")))).withColumn("b", F.least("b", F.col("a") + run - 1))
    placed = runs.withColumn("rank", F.explode(F.sequence("a", "b")))
    return placed.select(F.col("__id").alias(id_col), "size", "text_crc32", "shard", (F.col("base") + F.col("rank") - F.col("low")).alias("slot"))


def shard_report(docs: DataFrame, shards: int = 40) -> DataFrame:
    """The contract's columns under the law ``rows``: counts at most one apart."""
    return shard_rows(docs, shards=shards).select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
