"""Measures over changing data: streams that feed informativeness, dependency quality and entropy, and their batch twins."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.storage import folder

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def stream_of(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of event files as a stream."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def key_counts(events: DataFrame, key: str = "user_id") -> DataFrame:
    """Rows of each join value; the running input of informativeness."""
    return events.groupBy(key).agg(F.count("*").alias("n"))


def windowed_quality(events: DataFrame, width: str = "1 day", late: str = "10 minutes") -> DataFrame:
    """Class sizes of user -> event type in tumbling windows; `quality_of` folds them to one share a window."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    return marked.groupBy(F.window("ts", width).alias("w"), "user_id", "event_type").agg(F.count("*").alias("c")).select(F.col("w.start").alias("start"), "user_id", "event_type", "c")


def quality_of(classes: DataFrame) -> DataFrame:
    per = classes.groupBy("start", "user_id").agg(F.max("c").alias("m"), F.sum("c").alias("n"))
    return per.groupBy("start").agg(F.round(F.sum("m") / F.sum("n"), 6).alias("quality"))


def sliding_types(events: DataFrame, width: str = "1 hour", slide: str = "15 minutes", late: str = "10 minutes") -> DataFrame:
    """Counts of event types in sliding windows; `entropy_of` folds them."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    return marked.groupBy(F.window("ts", width, slide).alias("w"), "event_type").agg(F.count("*").alias("c")).select(F.col("w.start").alias("start"), "event_type", "c")


def entropy_of(types: DataFrame) -> DataFrame:
    per = types.groupBy("start").agg(F.sum("c").cast("double").alias("n"), F.sum(F.col("c") * F.log2("c")).alias("s"))
    return per.select("start", F.round(F.greatest(F.lit(0.0), F.log2("n") - F.col("s") / F.col("n")), 6).alias("entropy"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Sessions of each user: start, events and summed value."""
    marked = events.withWatermark("ts", late) if events.isStreaming else events
    per = marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"), F.sum("value").alias("value"))
    return per.select("user_id", F.col("w.start").alias("start"), "events", F.round("value", 4).alias("value"))


def run_to_table(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what is there now and returns its sink as a table (for complete, the last state)."""
    spark = stream.sparkSession
    name = f"live_{uuid.uuid4().hex[:12]}"
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{folder(spark)}/{name}").start()
    q.awaitTermination()
    return spark.table(name)


def incremental_counts(stream: DataFrame, path: str, key: str = "user_id") -> None:
    """Appends the key counts of every batch to a table; sums over it are the counts so far, without a rescan."""
    spark = stream.sparkSession

    def put(batch: DataFrame, n: int) -> None:
        key_counts(batch, key).withColumn("batch", F.lit(n)).write.mode("append").parquet(path)

    stream.writeStream.foreachBatch(put).trigger(availableNow=True).option("checkpointLocation", f"{folder(spark)}/{uuid.uuid4().hex}").start().awaitTermination()


class Drift:
    """Stateful processor: per key, the share of unmatched rows so far; emits a row when it passes the limit for the first time."""

    def __init__(self, limit: float):
        self.limit = limit

    def init(self, handle: Any) -> None:
        self.state = handle.getValueState("s", "n long, unmatched long, alerted boolean")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timers: Any) -> Iterator[pd.DataFrame]:  # noqa: N802
        n, unmatched, alerted = self.state.get() if self.state.exists() else (0, 0, False)
        for pdf in rows:
            n += len(pdf)
            unmatched += int((~pdf["matched"]).sum())
        passed = n > 0 and unmatched / n > self.limit
        self.state.update((n, unmatched, alerted or passed))
        if passed and not alerted:
            yield pd.DataFrame({"event_type": [key[0]], "share": [unmatched / n]})

    def close(self) -> None:
        pass


def drift_alerts(stream: DataFrame, customers: DataFrame, limit: float) -> DataFrame:
    """Event types whose share of rows without a customer passes the limit."""
    from pyspark.sql.streaming import StatefulProcessor

    known = customers.select(F.col("c_custkey").alias("user_id"), F.lit(True).alias("known"))
    marked = stream.join(known, "user_id", "left").select("event_type", F.col("known").isNotNull().alias("matched"))
    processor = type("DriftProcessor", (Drift, StatefulProcessor), {})(limit)
    return marked.groupBy("event_type").transformWithStateInPandas(statefulProcessor=processor, outputStructType="event_type string, share double", outputMode="Append", timeMode="None")


def _events(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/events.parquet")


def _late(spark: SparkSession, d: str) -> DataFrame:
    """Events that come after a watermark of ten minutes has passed them, in order of arrival by id: the batch twin."""
    e = _events(spark, d)
    bucket = F.floor(F.col("event_id") / 1000).alias("b")
    high = e.groupBy(bucket).agg(F.max("ts").alias("top"))
    so_far = high.select((F.col("b") + 1).alias("b"), F.max("top").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("seen"))  # one row a batch
    late = e.withColumn("b", F.floor(F.col("event_id") / 1000)).join(so_far, "b").where("ts < seen - interval 10 minutes")
    return late.agg(F.count("*").alias("late"))


QUERIES = {
    "stream_key_counts": (lambda spark, d: key_counts(_events(spark, d)), "SELECT user_id, count(*) n FROM events GROUP BY ALL"),
    "stream_window_quality": (lambda spark, d: quality_of(windowed_quality(_events(spark, d))), "SELECT start, round(sum(m) / sum(n), 6) quality FROM (SELECT start, user_id, max(c) m, sum(c)::DOUBLE n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') start, user_id, event_type, count(*) c FROM events GROUP BY ALL) GROUP BY ALL) GROUP BY ALL"),
    "stream_sliding_entropy": (lambda spark, d: entropy_of(sliding_types(_events(spark, d))), "SELECT start, round(greatest(0, log2(sum(c)) - sum(c * log2(c)) / sum(c)), 6) entropy FROM (SELECT start, event_type, count(*)::DOUBLE c FROM (SELECT time_bucket(INTERVAL 15 MINUTE, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 15 MINUTE start, event_type FROM events, range(4) r(k)) GROUP BY ALL) GROUP BY ALL"),
    "stream_sessions": (lambda spark, d: sessions(_events(spark, d)), "SELECT user_id, min(ts) start, count(*) events, round(sum(value), 4) value FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END new FROM events)) GROUP BY user_id, s"),
    "stream_late_rows": (_late, "SELECT count(*) late FROM (SELECT *, event_id // 1000 b FROM events) e JOIN (SELECT b + 1 b, max(top) OVER (ORDER BY b) seen FROM (SELECT event_id // 1000 b, max(ts) top FROM events GROUP BY ALL)) s USING (b) WHERE ts < seen - INTERVAL 10 MINUTE"),
}
