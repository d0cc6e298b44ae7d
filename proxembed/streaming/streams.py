"""Changing graphs: edges from the events table, as batch or stream."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import LongType, StructField, StructType

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def _shaped(rows: DataFrame) -> DataFrame:
    """Event time must be TIMESTAMP for a watermark; the key comes out of the JSON."""
    return rows.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").alias("k"))


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _shaped(spark.read.parquet(f"{sf_dir}/events.parquet"))


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream."""
    return _shaped(spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path))


def late_bound(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay)


def edge_windows(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(user_id, k, start, end, w): edge weights of tumbling or sliding windows."""
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy("user_id", "k", span.alias("x")).agg(F.count("*").alias("w")).select("user_id", "k", F.col("x.start").alias("start"), F.col("x.end").alias("end"), "w")


def edge_sessions(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", gap).alias("x")).agg(F.count("*").alias("w")).select("user_id", F.col("x.start").alias("start"), F.col("x.end").alias("end"), "w")


def co_events(a: DataFrame, b: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, a, b): events of one user, the second up to an hour after the first; for streams both sides need watermarks."""
    x = a.select(F.col("user_id"), F.col("event_id").alias("a"), F.col("ts").alias("t"))
    y = b.select(F.col("user_id").alias("other"), F.col("event_id").alias("b"), F.col("ts").alias("s"))
    return x.join(y, F.expr(f"user_id = other and s > t and s <= t + interval {within}")).select("user_id", "a", "b")


def dedupe(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return late_bound(events, delay).dropDuplicatesWithinWatermark(["event_id"])


class DegreeState(StatefulProcessor):
    """Running degree of a vertex: a count that expires when its time to live has passed."""

    ttl_ms = 7 * 24 * 3600 * 1000

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", StructType([StructField("n", LongType())]), ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n = (self.count.get()[0] if self.count.exists() else 0) + sum(len(x) for x in rows)
        self.count.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "deg": [n]})

    def close(self) -> None:
        pass


def running_degrees(events: DataFrame) -> DataFrame:
    """(user_id, deg) updates; needs the RocksDB state store."""
    return events.groupBy("user_id").transformWithStateInPandas(DegreeState(), "user_id long, deg long", "Update", "processingTime")


def train_on_changes(events: DataFrame, train_batch: Callable[[DataFrame, int], None], checkpoint: str):
    """A query that hands each micro-batch's merged edges to `train_batch`: walks start at changed edges, training resumes."""

    def each(rows: DataFrame, batch_id: int) -> None:
        edges = rows.groupBy("user_id", "k").agg(F.count("*").alias("w")).select(F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("a"), F.concat(F.lit("k:"), F.col("k")).alias("b"), "w")
        train_batch(edges, batch_id)

    return events.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def scored(events: DataFrame, vectors: DataFrame) -> DataFrame:
    """Stream-static join: (event_id, score) of each event's user and key under (key, u, c) vectors."""
    from proxembed.functions.vectors import sigmoid, vec_dot

    u = vectors.select(F.col("key").alias("ku"), F.col("u").cast("array<double>").alias("x"))
    v = vectors.select(F.col("key").alias("kv"), F.col("c").cast("array<double>").alias("y"))
    named = events.withColumns({"ku": F.concat(F.lit("u:"), F.col("user_id").cast("string")), "kv": F.concat(F.lit("k:"), F.col("k"))})
    return named.join(u, "ku").join(v, "kv").select("event_id", sigmoid(vec_dot(F.col("x"), F.col("y"))).alias("score"))
