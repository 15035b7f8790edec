"""Online search over a stream of query events, and the windows, joins and state that go with it."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery

from neargraph.operators import shard
from neargraph.params import SearchParams, choose_mode

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, *, delay: str = "1 hour", files_per_batch: int = 1) -> DataFrame:
    """Events from Parquet files as they come; rows later than the delay are dropped, repeated ids too."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return raw.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def search_stream(events: DataFrame, index: DataFrame, vectors: DataFrame, out: str, checkpoint: str, params: SearchParams, *, b_t: int | None = None) -> StreamingQuery:
    """Each micro-batch is one search, its mode chosen by its size; a batch that is done again overwrites its own folder."""

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        queries = batch.join(vectors, batch.user_id == vectors.id).select(F.col("event_id").alias("qid"), "vec")
        mode = choose_mode(queries.count(), params.M, b_t=b_t or spark.sparkContext.defaultParallelism)
        hits = shard.search(index, queries, params, mode=mode).withColumn("mode", F.lit(mode))
        hits.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return events.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    return events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def views_to_purchases(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Views and the purchases of the same user within a time after them; both sides carry the watermark of the stream."""
    view = events.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("view_ts"))
    buy = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("buyer"), F.col("ts").alias("purchase_ts"))
    when = F.expr(f"user_id = buyer AND purchase_ts >= view_ts AND purchase_ts <= view_ts + INTERVAL {within}")
    return view.join(buy, when).select("view_id", "purchase_id", "user_id")


class RecentQueries(StatefulProcessor):
    """Keeps the last few query ids of each user and forgets a user after a time without any."""

    KEEP, EXPIRE_MS = 5, 6 * 3600 * 1000

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.recent = handle.getValueState("recent", "ids array<long>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = list(self.recent.get()[0]) if self.recent.exists() else []
        for pdf in rows:
            held += pdf.sort_values("ts")["event_id"].tolist()
        held = held[-self.KEEP :]
        self.recent.update((held,))
        now = timerValues.getCurrentWatermarkInMs()
        for timer in self.handle.listTimers():
            self.handle.deleteTimer(timer)
        self.handle.registerTimer(max(now, 0) + self.EXPIRE_MS)
        yield pd.DataFrame({"user_id": [key[0]], "n_recent": [len(held)], "last_event": [held[-1]]})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        self.recent.clear()
        yield from ()

    def close(self) -> None:
        return None


def recent_queries(events: DataFrame) -> DataFrame:
    """Needs the RocksDB state store."""
    return events.groupBy("user_id").transformWithStateInPandas(RecentQueries(), "user_id long, n_recent long, last_event long", "Update", "EventTime")
