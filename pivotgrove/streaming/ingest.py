"""Streams: continuous insertion, windows, dedupe, stateful counts, queries against a pinned version."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from pivotgrove.operators.index import IndexHandle
from pivotgrove.operators.insertion import insert_batch
from pivotgrove.operators.search import knn
from pivotgrove.sources import store
from pivotgrove.sources.points import EVENT_SCHEMA, view_of


def events_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of event files as a stream, with ts_utc for watermarks (they need a zoned timestamp)."""
    raw = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return with_utc(raw)


def with_utc(events: DataFrame) -> DataFrame:
    return events.withColumn("ts_utc", F.timestamp_micros(F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)")))


class IndexHolder:
    """The current version of an index under a stream; a batch that comes again changes nothing.

    With a path every version is saved there with the batches it holds, so that reopened() knows them after a restart.
    """

    def __init__(self, ix: IndexHandle, on_version: Callable[[IndexHandle], None] | None = None, path: str | None = None, seen: set[int] | None = None):
        self.ix, self.seen, self.on_version, self.path = ix, set(seen or ()), on_version, path

    @classmethod
    def reopened(cls, spark: SparkSession, path: str, on_version: Callable[[IndexHandle], None] | None = None) -> IndexHolder:
        return cls(store.load(spark, path), on_version, path, store.batches(spark, path))

    def take(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id in self.seen:
            return
        self.ix = insert_batch(self.ix, batch)
        self.seen.add(batch_id)
        if self.path:
            store.save(self.ix, self.path, sorted(self.seen))
        if self.on_version:
            self.on_version(self.ix)


def stream_insert(events: DataFrame, holder: IndexHolder, checkpoint: str, view: str = "evt2") -> StreamingQuery:
    """Insert a stream of events by micro-batches until the input is used up; call awaitTermination on the result."""
    return view_of(events, view).writeStream.foreachBatch(holder.take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stream_knn(queries: DataFrame, holder: IndexHolder, sink: Callable[[DataFrame, int], None], checkpoint: str) -> StreamingQuery:
    """Answer a stream of queries (qid, qcoords, k) against the holder's version at each micro-batch."""
    return queries.writeStream.foreachBatch(lambda batch, i: sink(knn(holder.ix, batch), i)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def tumbling(events: DataFrame, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Arrivals by window and type."""
    seen = events.withWatermark("ts_utc", late) if events.isStreaming else events
    out = seen.groupBy(F.window("ts_utc", length), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "event_type", "n", F.round("total", 4).alias("total"))


def sliding(events: DataFrame, length: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    seen = events.withWatermark("ts_utc", late) if events.isStreaming else events
    return seen.groupBy(F.window("ts_utc", length, step)).agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "n")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    """Each user's runs of events without a pause of the gap."""
    seen = events.withWatermark("ts_utc", late) if events.isStreaming else events
    out = seen.groupBy("user_id", F.session_window("ts_utc", gap).alias("s")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("s.start").cast("timestamp_ntz").alias("session_start"), "n")


def deduped(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Replayed events once."""
    if events.isStreaming:
        return events.withWatermark("ts_utc", late).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def cell_counts(events: DataFrame, width: float) -> DataFrame:
    """Running counts of events by value cell (update mode): the size audit in flight."""
    return events.groupBy(F.floor(F.col("value") / width).alias("cell")).agg(F.count("*").alias("n"))


def stateful_cell_counts(events: DataFrame, width: float) -> DataFrame:
    """The same counts kept by hand in the state store: one row a cell and micro-batch, (cell, n so far)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def add(key, frames, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"cell": [key[0]], "n": [n]})

    keyed = events.select(F.floor(F.col("value") / width).alias("cell"), "event_id")
    return keyed.groupBy("cell").applyInPandasWithState(add, "cell long, n long", "n long", "update", GroupStateTimeout.NoTimeout)


def interval_pairs(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Events of one user on both sides within an interval after the left one; both streams have watermarks."""
    a = left.withWatermark("ts_utc", late).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts_utc").alias("a_ts"))
    b = right.withWatermark("ts_utc", late).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts_utc").alias("b_ts"))
    return a.join(b, F.expr(f"a_user = b_user and b_ts > a_ts and b_ts <= a_ts + interval {within}")).select("a_id", "b_id")


def run_to_table(stream: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Run a stream over what is there and give its table: appended rows in files beside the checkpoint, other modes (a row a group) in memory."""
    if mode == "append":
        sink = stream.writeStream.outputMode(mode).format("parquet").option("path", f"{checkpoint}-out")
        sink.option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
        return stream.sparkSession.read.schema(stream.schema).parquet(f"{checkpoint}-out")
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
