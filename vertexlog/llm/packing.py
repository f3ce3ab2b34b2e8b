"""Packing of token sequences by patterns fitted to the length histogram.

Lengths fall into bins; every pattern of one to three bins that fills a sequence is a column of a matrix, and
non-negative least squares finds how often each should be repeated to use up the histogram.  Repeat counts are
rounded down.  Each pattern is then made of exact lengths: the last document of a pattern is the longest that
still fits.  What is left is packed best-fit, longest first, also into gaps that patterns leave.  All of this
works on counts per length, of which there are no more than the sequence is long, so the plan has a bounded size
however many documents there are.

Plan: tokenizing is one pass without a shuffle into a narrow table of pieces.  A piece's rank among those of
its length is its rank within length and input partition plus the counts before, so a length that a third of all
pieces share is not gathered.  The plan is broadcast; ranks become places by binary search.

Defined results: null text is the end mark alone; repeated rows are packed one by one; texts longer than a
sequence are cut into whole sequences behind a first piece that may be shorter; no rows give no sequences.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from vertexlog.llm.common import Scratch

PIECE = "piece int, start bigint, length bigint, ids_crc32 bigint"
PLACED = "sequence_id bigint, offset bigint"


def cut(tokens: int, limit: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a document; only the first may be shorter than the limit."""
    first = tokens % limit or min(tokens, limit)
    return [(0, first), *((s, limit) for s in range(first, tokens, limit))] if tokens else []


def nnls(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Non-negative x that minimises |ax - b|, by active sets."""
    x, on = np.zeros(a.shape[1]), np.zeros(a.shape[1], bool)
    gram, target = a.T @ a, a.T @ b
    for _ in range(2 * a.shape[0]):
        slope = target - gram @ x
        slope[on] = 0
        best = int(np.argmax(slope))
        if slope[best] <= 1e-9 * max(1.0, b.max()):
            break
        on[best] = True
        while True:
            z = np.zeros_like(x)
            z[on] = np.linalg.solve(gram[np.ix_(on, on)] + 1e-9 * np.eye(int(on.sum())), target[on])
            low = on & (z <= 0)
            if not low.any():
                break
            step = (x[low] / np.maximum(x[low] - z[low], 1e-12)).min()
            x = x + step * (z - x)
            on &= x > 1e-12 * max(1.0, x.max())
            x[~on] = 0
        x = z
    return x


def patterns(bins: int, used: np.ndarray) -> list[tuple[int, ...]]:
    """Multisets of one to three used bins (numbered from 1) whose upper edges add up to a full sequence."""
    out = [(bins,)] if used[bins] else []
    out += [(a, bins - a) for a in range(bins - 1, (bins - 1) // 2, -1) if used[a] and used[bins - a]]
    for a in range(bins - 2, 0, -1):
        for b in range(min(a, bins - a - 1), (bins - a - 1) // 2, -1):
            if used[a] and used[b] and used[bins - a - b] and bins - a - b <= b:
                out.append((a, b, bins - a - b))
    return out


class Plan:
    """Groups of equal sequences: how many, and the lengths in each; made from counts per length."""

    def __init__(self, counts: np.ndarray, bins: int = 128) -> None:
        self.limit = len(counts) - 1
        self.left = counts.astype(np.int64).copy()
        self.bins = min(bins, self.limit)
        self.open: dict[int, list[tuple[int, tuple[tuple[int, int], ...]]]] = defaultdict(list)
        self._fit()
        self._best_fit()

    def _add(self, times: int, lengths: tuple[tuple[int, int], ...]) -> None:
        self.open[self.limit - sum(n * m for n, m in lengths)].append((times, lengths))

    def _fit(self) -> None:
        edge = -(-np.arange(self.limit + 1) * self.bins // self.limit)
        per_bin = np.bincount(edge, weights=self.left, minlength=self.bins + 1)
        made = patterns(self.bins, per_bin > 0)
        if not made:
            return
        a = np.zeros((self.bins, len(made)))
        for j, p in enumerate(made):
            for b in p:
                a[b - 1, j] += 1
        repeats = np.floor(nnls(a, per_bin[1:]) + 1e-9).astype(np.int64)
        members = [np.flatnonzero(edge == b) for b in range(self.bins + 1)]
        for j in np.argsort([-max(p) for p in made], kind="stable"):
            self._make(made[j], int(repeats[j]), members)

    def _longest(self, among: np.ndarray | None, most: int) -> int:
        if among is None:
            found = np.flatnonzero(self.left[: most + 1])
        else:
            found = among[(self.left[among] > 0) & (among <= most)]
        return int(found[-1]) if len(found) else 0

    def _make(self, pattern: tuple[int, ...], times: int, members: list[np.ndarray]) -> None:
        while times > 0:
            chosen: list[int] = []
            for k, b in enumerate(pattern):
                room = self.limit - sum(chosen)
                last = k == len(pattern) - 1
                for n in chosen:
                    self.left[n] -= 1
                n = self._longest(None if last and k else members[b], room)
                for c in chosen:
                    self.left[c] += 1
                if not n:
                    break
                chosen.append(n)
            if not chosen or len(chosen) < len(pattern):
                return
            each = [(n, chosen.count(n)) for n in dict.fromkeys(chosen)]
            now = min(times, *(int(self.left[n]) // m for n, m in each))
            for n, m in each:
                self.left[n] -= now * m
            self._add(now, tuple(each))
            times -= now

    def _best_fit(self) -> None:
        free = np.zeros(self.limit + 1, bool)
        for f, groups in self.open.items():
            free[f] = bool(groups)
        for n in np.flatnonzero(self.left)[::-1].tolist():
            if n == 0:
                continue
            count = int(self.left[n])
            while count:
                fits = np.flatnonzero(free[n:])
                if not len(fits):
                    per = self.limit // n
                    if count >= per:
                        self._add(count // per, ((n, per),))
                        free[self.limit - n * per] = True
                        count %= per
                    if count:
                        self._add(1, ((n, count),))
                        free[self.limit - n * count] = True
                    break
                f = n + int(fits[0])
                times, lengths = self.open[f].pop()
                now, per = min(times, count), 1
                if count >= times * (f // n):
                    now, per = times, f // n
                if now < times:
                    self.open[f].append((times - now, lengths))
                merged = dict(lengths)
                merged[n] = merged.get(n, 0) + per
                self._add(now, tuple(merged.items()))
                free[f] = bool(self.open[f])
                free[f - n * per] = True
                count -= now * per
        self.left[:] = 0

    def table(self) -> np.ndarray:
        """Rows (length, first rank, first sequence, offset, copies in a sequence), sorted by length and rank."""
        used: dict[int, int] = defaultdict(int)
        rows, sequence = [], 0
        for f in sorted(self.open):
            for times, lengths in self.open[f]:
                offset = 0
                for n, m in lengths:
                    rows.append((n, used[n], sequence, offset, m))
                    used[n] += times * m
                    offset += n * m
                sequence += times
        self.sequences = sequence
        return np.array(sorted(rows), np.int64).reshape(-1, 5)


def pieces(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048, end_id: int = 0, vocabulary: str = "byte_bpe_50k") -> DataFrame:
    """(id, piece, start, length, ids_crc32) for every piece of every document."""
    schema = T.StructType([docs.schema[id_col], *T._parse_datatype_string(PIECE).fields])
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from vertexlog.llm.tokens import encoder

        ids_of = encoder(vocabulary).ids
        for batch in batches:
            at, rows = [], []
            for i, text in enumerate(batch.column(1)):
                ids = ids_of(text.as_py() or "") + end
                for k, (start, n) in enumerate(cut(len(ids) // 4, limit)):
                    at.append(i)
                    rows.append((k, start, n, zlib.crc32(ids[4 * start : 4 * (start + n)])))
            columns = zip(*rows, strict=True) if rows else ([], [], [], [])
            made = [pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at, pa.int64())), *made], names=schema.names)

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def pack(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", limit: int = 2048, end_id: int = 0, vocabulary: str = "byte_bpe_50k", bins: int = 128) -> DataFrame:
    """One row per piece: id, piece, start, length, ids_crc32, sequence_id and offset."""
    spark = docs.sparkSession
    cut_up = pieces(docs, id_col=id_col, text_col=text_col, limit=limit, end_id=end_id, vocabulary=vocabulary)
    rows = Scratch(spark, "pieces").keep(cut_up.withColumn("__part", F.spark_partition_id()))
    counts = rows.groupBy("length", "__part").agg(F.count("*").alias("n"))
    histogram = np.zeros(limit + 1, np.int64)
    for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most ``limit`` rows
        histogram[r["length"]] = r["n"]
    shared = spark.sparkContext.broadcast(Plan(histogram, bins).table())
    before = counts.select("length", "__part", (F.sum("n").over(Window.partitionBy("length").orderBy("__part")) - F.col("n")).alias("__before"))
    own = F.row_number().over(Window.partitionBy("length", "__part").orderBy(id_col, "piece", "ids_crc32")) - 1
    ranked = rows.withColumn("__own", own).join(before, ["length", "__part"])
    names = [id_col, "piece", "start", "length", "ids_crc32"]
    ranked = ranked.select(*names, (F.col("__own") + F.col("__before")).cast("bigint").alias("__rank"))
    schema = T.StructType([*(rows.schema[c] for c in names), *T._parse_datatype_string(PLACED).fields])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        key = (table[:, 0] << 44) | table[:, 1]
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            hit = table[np.searchsorted(key, (length << 44) | rank, "right") - 1]
            nth = rank - hit[:, 1]
            sequence, offset = hit[:, 2] + nth // hit[:, 4], hit[:, 3] + nth % hit[:, 4] * length
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], names=schema.names)

    return ranked.mapInArrow(place, schema)
