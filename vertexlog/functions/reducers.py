"""Reduce operators: pairs (lift, merge) of which merge is binary and associative."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Reducer:
    """How values of one destination become one.

    ``lift`` aggregates raw values, ``merge`` aggregates what ``lift`` made; both take (value, order) columns.
    ``ordered`` reducers depend on the order of the log and need its ordinals.  ``pair`` folds two values one by one,
    after ``unit`` has made a single value of a record.
    """

    name: str
    lift: Callable[[Column, Column], Column]
    merge: Callable[[Column, Column], Column] | None = None
    ordered: bool = False
    pair: Callable[[object, object], object] | None = field(default=None, compare=False)
    unit: Callable[[object], object] = field(default=lambda x: x, compare=False)

    def again(self) -> Callable[[Column, Column], Column]:
        return self.merge or self.lift


def _plain(name: str, agg: Callable[[Column], Column], pair: Callable, merge: Callable[[Column], Column] | None = None, unit: Callable[[object], object] = lambda x: x) -> Reducer:
    return Reducer(name, lambda v, o: agg(v), (lambda v, o: merge(v)) if merge else None, pair=pair, unit=unit)


REDUCERS = {
    r.name: r
    for r in (
        _plain("sum", F.sum, lambda a, b: a + b),
        _plain("min", F.min, min),
        _plain("max", F.max, max),
        _plain("count", F.count, lambda a, b: a + b, F.sum, lambda x: 1),
        _plain("any", F.bool_or, lambda a, b: a or b),
        _plain("all", F.bool_and, lambda a, b: a and b),
        _plain("bit_or", F.bit_or, lambda a, b: a | b),
        _plain("bit_and", F.bit_and, lambda a, b: a & b),
        _plain("bit_xor", F.bit_xor, lambda a, b: a ^ b),
        _plain("product", lambda v: F.product(v), lambda a, b: a * b),
        _plain("collect_distinct", lambda v: F.sort_array(F.collect_set(v)), lambda a, b: sorted({*a, *b}), lambda v: F.sort_array(F.array_distinct(F.flatten(F.collect_list(v)))), lambda x: [x]),
        Reducer("first", lambda v, o: F.min_by(v, o), ordered=True, pair=lambda a, b: a),
        Reducer("last", lambda v, o: F.max_by(v, o), ordered=True, pair=lambda a, b: b),
        Reducer("min_by", lambda v, o: F.min_by(v, o), ordered=True),
        Reducer("max_by", lambda v, o: F.max_by(v, o), ordered=True),
    )
}


def check_associative(spark: SparkSession, pair: Callable[[int, int], int], samples: list[int], tol: float = 0.0) -> DataFrame:
    """Every triple of the samples with both ways of folding it and whether they agree."""
    rows = []
    for a in samples:
        for b in samples:
            for c in samples:
                left, right = pair(pair(a, b), c), pair(a, pair(b, c))
                rows.append((a, b, c, left, right, abs(left - right) <= tol))
    return spark.createDataFrame(rows, "a bigint, b bigint, c bigint, left_first bigint, right_first bigint, ok boolean")


def fold_in_blocks(log: DataFrame, pair: Callable, block: int = 100_000, in_order: bool = False) -> DataFrame:
    """Log (dst, val) folded by any Python function of two values, block by block within each task.

    ``in_order``: rows come sorted by destination, so that only the last key is open when a block ends.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}
        kinds = None
        for batch in batches:
            kinds = batch.schema
            for k, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held[k] = pair(held[k], v) if k in held else v
            if len(held) >= block:
                last = {k: held.pop(k)} if in_order else {}
                yield _batch(held, kinds)
                held = last
        if held:
            yield _batch(held, kinds)

    return log.select("dst", "val").mapInArrow(run, log.select("dst", "val").schema)


def _batch(held: dict, kinds: pa.Schema) -> pa.RecordBatch:
    keys = sorted(held)
    return pa.RecordBatch.from_arrays([pa.array(keys, kinds.field(0).type), pa.array([held[k] for k in keys], kinds.field(1).type)], names=["dst", "val"])


def custom(log: DataFrame, pair: Callable) -> DataFrame:
    """Fold by a user's associative function: block fold, exchange by key, then fold again.

    A log with ``ord`` is folded in its order, so the function need not be commutative: tasks take ranges of places,
    hence what a task folds of a destination is one run of its records, and runs meet again in order.
    """
    if "ord" not in log.columns:
        return fold_in_blocks(fold_in_blocks(log, pair).repartition("dst").sortWithinPartitions("dst"), pair, in_order=True)
    runs = log.repartitionByRange("ord").sortWithinPartitions("ord")
    numbered = fold_in_blocks(runs, pair).withColumn("ord", F.monotonically_increasing_id())
    return fold_in_blocks(numbered.repartition("dst").sortWithinPartitions("dst", "ord"), pair, in_order=True)
