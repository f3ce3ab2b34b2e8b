"""What a round costs: reduction per merge phase, data moved, pages touched, edges scanned, accuracy."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexlog.operators.sortreduce import merge_phases
from vertexlog.sources.scratch import Scratch
from vertexlog.sources.tables import ordinal


def reduction_curve(destinations: DataFrame, m: int, n: int, k: int, at_once: int = 50_000_000) -> DataFrame:
    """(phase, blocks, records, fraction) of an interleaved fold of a log (dst, ord) of m records.

    Phase 0 is the log itself, phase 1 what block folds leave, each later one a merge of k blocks.  Short logs are
    counted in one pass, a record once for each phase and block in which its destination occurs; for longer ones
    every phase is written and the next one folds what it left.
    """
    sizes = [n * k**p for p in range(merge_phases(m, n, k) + 1)]
    if m * len(sizes) <= at_once:
        at = F.array(*(F.struct(F.lit(p + 1).alias("phase"), F.expr(f"ord div {s}").alias("block")) for p, s in enumerate(sizes)))
        rows = destinations.select("dst", F.explode(at).alias("x")).select("x.phase", "x.block", "dst").distinct()
        later = rows.groupBy("phase").agg(F.countDistinct("block").alias("blocks"), F.count("*").alias("records"))
    else:
        scratch, later = Scratch(destinations.sparkSession, "phases"), None
        left = destinations.select(F.expr(f"ord div {n}").alias("block"), "dst").distinct()
        for p in range(len(sizes)):
            left = scratch.keep(left if p == 0 else left.select(F.expr(f"block div {k}").alias("block"), "dst").distinct())
            row = left.agg(F.lit(p + 1).alias("phase"), F.countDistinct("block").alias("blocks"), F.count("*").alias("records"))
            later = row if later is None else later.unionByName(row)
    first = destinations.agg(F.count("*").alias("records")).select(F.lit(0).alias("phase"), F.lit(-(-m // n)).cast("bigint").alias("blocks"), "records")
    return first.unionByName(later).select("phase", "blocks", "records", (F.col("records") / F.lit(float(m))).alias("fraction"))


def log_of(edges: DataFrame) -> DataFrame:
    """(dst, ord) of a log that all vertices write, in emission order."""
    return ordinal(edges.select("src", "dst"), "src", "dst").select("dst", "ord")


def movement_ratio(curve: DataFrame) -> DataFrame:
    """(phases, ratio): records written when folding while merging, by those of sorting first."""
    row = curve.agg(
        (F.max("phase") - 1).cast("int").alias("phases"),
        (F.sum(F.when(F.col("phase") > 0, F.col("records"))) / (F.max(F.when(F.col("phase") == 0, F.col("records"))) * F.max("phase"))).alias("ratio"),
    )
    return row


def page_reads(destinations: DataFrame, record: int = 8, page: int = 8192) -> DataFrame:
    """(sorted_pages, random_pages, log): pages read when updates come sorted or in log order."""
    place = F.expr(f"dst * {record} div {page}")
    # neighbours in log order are found by a self join on the ordinal, not by a window over the whole log
    a = destinations.select("ord", place.alias("page"))
    b = a.select((F.col("ord") + 1).alias("ord"), F.col("page").alias("before"))
    random = a.join(b, "ord", "left").agg(F.count(F.when(F.col("before").isNull() | (F.col("before") != F.col("page")), 1)).alias("random_pages"), F.count("*").alias("log"))
    return a.agg(F.countDistinct("page").alias("sorted_pages")).crossJoin(random)


def compare(a: DataFrame, b: DataFrame, key: str = "v", val: str = "val") -> DataFrame:
    """(metric, value): sup, L1 and L2 distance of two lists; a missing vertex counts as zero."""
    x, y = a.select(key, F.col(val).cast("double").alias("x")), b.select(key, F.col(val).cast("double").alias("y"))
    gap = x.join(y, key, "full").select(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))).alias("d"))
    row = gap.agg(F.coalesce(F.max("d"), F.lit(0.0)).alias("sup"), F.coalesce(F.sum("d"), F.lit(0.0)).alias("l1"), F.sqrt(F.coalesce(F.sum(F.col("d") * F.col("d")), F.lit(0.0))).alias("l2"))
    return row.select(F.expr("stack(3, 'sup', sup, 'l1', l1, 'l2', l2) as (metric, value)"))


def top_overlap(a: DataFrame, b: DataFrame, k: int, key: str = "v", val: str = "val") -> float:
    """Share of the k best of one list that are among the k best of the other."""
    best = lambda d: d.orderBy(F.desc(val), key).limit(k).select(key)
    return best(a).intersect(best(b)).count() / max(1, k)


def same(a: DataFrame, b: DataFrame) -> bool:
    cols = a.columns
    return a.exceptAll(b.select(cols)).isEmpty() and b.select(cols).exceptAll(a).isEmpty()


def stage_totals(spark: SparkSession, action: Callable[[], object]) -> dict[str, float]:
    """What the stages of an action report: seconds, processor seconds, rows and bytes read, bytes moved and written.

    Sums of task metrics over the stages that ran meanwhile; a stage that is skipped counts nothing.
    """
    context = spark.sparkContext._jsc.sc()

    def stages() -> dict[int, object]:
        context.listenerBus().waitUntilEmpty()
        found = context.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), spark.sparkContext._jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): s for s in (found.apply(i) for i in range(found.size()))}

    before, start = set(stages()), time.perf_counter()
    action()
    seconds = time.perf_counter() - start
    ran = [s for key, s in stages().items() if key not in before]
    total = lambda f: float(sum(f(s) for s in ran))
    return {
        "seconds": seconds,
        "cpu_seconds": total(lambda s: s.executorCpuTime()) / 1e9,
        "rows_read": total(lambda s: s.inputRecords()),
        "bytes_read": total(lambda s: s.inputBytes()),
        "bytes_logged": total(lambda s: s.shuffleWriteBytes()),
        "bytes_merged": total(lambda s: s.shuffleReadBytes()),
        "bytes_written": total(lambda s: s.outputBytes()),
        "bytes_spilled": total(lambda s: s.diskBytesSpilled()),
    }


def scan_efficiency(sizes: list[int], useful: list[int], read: list[int], edges: int, intervals: int = 4) -> list[tuple[str, int, int, int, int]]:
    """(engine, step, active, edges read, edges useful): ranges opened, edge scan, several passes."""
    out = []
    for step, (active, used, opened) in enumerate(zip(sizes, useful, read, strict=True), start=1):
        out += [("sort_reduce", step, active, opened, used), ("edge_scan", step, active, edges, used), ("multi_pass", step, active, edges * intervals, used)]
    return out
