"""Edges that arrive as a stream: windows of folds, incremental vertex lists, state per user, joins.

Every query reads the event table as a file stream until it has seen all of it and returns the final result, so
it can be held against the same aggregate in batch.
"""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQueryListener
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from vertexlog.operators.updatelog import UpdateLog
from vertexlog.sources.scratch import Scratch, shared_dir
from vertexlog.sources.tables import load


def source(spark: SparkSession, path: str, like: DataFrame, files_per_trigger: int = 1) -> DataFrame:
    """Files of a directory or pattern as an event stream of fixed schema, a few files at a time."""
    return spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


class _LateRows(StreamingQueryListener):
    """Adds up what the watermark drops, over all batches of every query it hears of."""

    def __init__(self) -> None:
        self.dropped: dict[str, int] = {}
        self.ended: set[str] = set()
        self.told = threading.Condition()

    def onQueryStarted(self, event: object) -> None: ...

    def onQueryIdle(self, event: object) -> None: ...

    def onQueryProgress(self, event: object) -> None:
        run = str(event.progress.runId)
        self.dropped[run] = self.dropped.get(run, 0) + sum(s.numRowsDroppedByWatermark for s in event.progress.stateOperators)

    def onQueryTerminated(self, event: object) -> None:
        with self.told:
            self.ended.add(str(event.runId))
            self.told.notify_all()

    def count(self, run: str, seconds: float = 60) -> int:
        """What a run that has ended dropped; events come in order, some time after the query itself has ended."""
        with self.told:
            if not self.told.wait_for(lambda: run in self.ended, seconds):
                raise TimeoutError("the end of the query was not reported, so its count of late rows is not known")
        return self.dropped.get(run, 0)


def drain(stream: DataFrame, sink: Callable[[DataFrame, int], None], mode: str = "append", checkpoint: str | None = None) -> int:
    """Run a streaming query over all that is there now; the sink gets each micro-batch and its number.

    Returns how many rows came behind the watermark and were dropped.  Spark counts them as they reach the state, so
    late rows of one window and key that a map task has folded count once.  ``checkpoint`` names the folder from which
    a later call goes on; otherwise each call reads everything.
    """
    spark, late = stream.sparkSession, _LateRows()
    where = checkpoint or f"{shared_dir(spark)}/vertexlog/stream-{uuid.uuid4().hex}"
    spark.streams.addListener(late)
    try:
        query = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", where).trigger(availableNow=True).start()
        query.awaitTermination()
        return late.count(str(query.runId))
    finally:
        spark.streams.removeListener(late)


def collected(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All rows a stream has put out; with complete mode those of the last batch."""
    spark = stream.sparkSession
    scratch, parts = Scratch(spark, "sink"), {}

    def put(batch: DataFrame, number: int) -> None:
        parts[number] = scratch.keep(batch, f"batch={number}-{uuid.uuid4().hex}")

    drain(stream, put, mode)
    if not parts:
        return spark.createDataFrame([], stream.schema)
    kept = [parts[max(parts)]] if mode == "complete" else [parts[k] for k in sorted(parts)]
    out = kept[0]
    for p in kept[1:]:
        out = out.unionByName(p)
    return out


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as files of a pattern, with times that watermarks accept."""
    stream = source(spark, f"{sf_dir}/events.parquet*", load(spark, sf_dir, "events"))
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_fold(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events folded per time window and user; later than ``late`` they are dropped."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), F.col("user_id").alias("dst")).agg(F.count("*").alias("n"))


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = collected(windowed_fold(_events(spark, sf_dir), "1 day"), "complete")
    return done.select(F.col("w.start").cast("timestamp_ntz").alias("day"), "dst", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = collected(windowed_fold(_events(spark, sf_dir), "2 days", "1 day"), "complete")
    return done.groupBy("dst").agg(F.sum("n").alias("n"))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = _events(spark, sf_dir).withWatermark("ts", "1 hour")
    done = collected(events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")), "complete")
    return done.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def state_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One update list per micro-batch, each written once however often the batch is retried; newest wins."""
    log, done = UpdateLog(spark, "stream-lists"), set()

    def put(batch: DataFrame, number: int) -> None:
        if number not in done:
            log.append(number, batch.groupBy(F.col("user_id").alias("v")).agg(F.max_by("event_id", "ts").alias("val")))
            done.add(number)
            log.compact_if(8)

    drain(_events(spark, sf_dir), put)
    return log.resolve().select("v", "val")


def chain_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge from the previous event of the same user to each event, kept as state per user."""

    def link(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values("ts")["event_id"].tolist()
        pairs = list(zip([before, *rows[:-1]], rows, strict=True))
        state.update((rows[-1],))
        yield pd.DataFrame([p for p in pairs if p[0] is not None], columns=["src", "dst"]).astype("int64")

    events = _events(spark, sf_dir).select("user_id", "event_id", "ts")
    linked = events.groupBy("user_id").applyInPandasWithState(link, "src bigint, dst bigint", "last bigint", "append", GroupStateTimeout.NoTimeout)
    return collected(linked)


def with_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events joined to customers as they come, then counted by segment."""
    customers = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return collected(_events(spark, sf_dir).join(customers, "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First event of every user and type within the watermark."""
    events = _events(spark, sf_dir).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return collected(events.select("user_id", "event_type"))


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Views followed by a purchase of the same user within an hour, both sides streams."""
    a = _events(spark, sf_dir).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("src"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    b = _events(spark, sf_dir).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("dst"), "ts").withWatermark("ts", "1 hour")
    near = (F.col("u") == F.col("user_id")) & (F.col("ts") > F.col("t1")) & (F.col("ts") <= F.col("t1") + F.expr("interval 1 hour"))
    return collected(a.join(b, near).select("src", "dst"))


def as_of(events: DataFrame) -> DataFrame:
    """Each view with the last purchase before it, found day by day.

    A purchase at the time of the view is not before it; of purchases at one time the largest id counts.  Within a day
    a window looks back; views before a day's first purchase get the last purchase of earlier days, of which there is
    one row per day.
    """
    day = events.where("ts is not null").withColumn("day", F.to_date("ts"))
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    before = F.last(bought, ignorenulls=True).over(Window.partitionBy("day").orderBy("ts", F.col("event_type") == "purchase", "event_id").rowsBetween(Window.unboundedPreceding, -1))
    inside = day.withColumn("p", before)
    per_day = day.groupBy("day").agg(F.max(bought).alias("last"))
    earlier = per_day.withColumn("e", F.last("last", ignorenulls=True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1))).select("day", "e")
    found = inside.where("event_type = 'view'").join(earlier, "day").select(F.coalesce("p", "e")["event_id"].alias("src"), F.col("event_id").alias("dst"))
    return found.where("src is not null")


QUERIES = {
    "stream_tumbling": (tumbling, "select date_trunc('day', ts)::timestamp as day, user_id as dst, count(*) as n from events group by 1, 2"),
    "stream_sliding": (sliding, "select user_id as dst, 2 * count(*) as n from events group by 1"),
    "stream_sessions": (
        sessions,
        "select user_id, sum(s)::bigint as sessions, count(*) as events from (select user_id, case when ts < lag(ts) over (partition by user_id order by ts) + interval 30 minutes then 0 else 1 end as s from events) group by user_id",
    ),
    "stream_state_lists": (state_lists, "select user_id as v, max_by(event_id, ts) as val from events group by 1"),
    "stream_chain_edges": (chain_edges, "select src, dst from (select event_id as src, lead(event_id) over (partition by user_id order by ts) as dst from events) where dst is not null"),
    "stream_static_join": (with_static, "select c_mktsegment, count(*) as n from events join customer on c_custkey = user_id group by 1"),
    "stream_dedup": (deduplicated, "select distinct user_id, event_type from events"),
    "stream_stream_join": (
        stream_join,
        "select a.event_id as src, b.event_id as dst from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'view' and b.event_type = 'purchase'",
    ),
}
