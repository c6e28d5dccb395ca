"""Sketch states of event time windows: batch twins, and Structured Streaming forms with the same integers."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.hashing import bucket, coin, string_key, uniform_int
from ..params import Params, threshold
from ..sources.tables import SCHEMAS


def stream_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A directory of event files as a stream, event time as a timestamp (in UTC) that watermarks accept."""
    rows = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def event_clients(events: DataFrame) -> DataFrame:
    """rid, item, key, ts, user_id of every event."""
    return events.select(F.col("event_id").cast("string").alias("rid"), F.col("event_type").alias("item"), string_key(F.col("event_type")).alias("key"), "ts", "user_id")


def event_reports(events: DataFrame, p: Params) -> DataFrame:
    """rid, ts, j, l, sign: the one-sign reports of a stream or a table of events (append mode)."""
    keyed = event_clients(events)
    rid = F.col("rid")
    drawn = keyed.select("rid", "ts", "user_id", "key", uniform_int(rid, p, "row", p.k).cast("int").alias("j"), uniform_int(rid, p, "coordinate", p.m).cast("int").alias("l"))
    parity = F.bit_count(F.col("l").cast("bigint").bitwiseAND(bucket(F.col("key"), F.col("j"), p))) % 2
    flipped = coin(rid, p, "flip") < threshold(p.hadamard_q)
    return drawn.select("rid", "ts", "user_id", "j", "l", F.when(flipped, 2 * parity - 1).otherwise(1 - 2 * parity).cast("int").alias("sign"))


def window_sketch(rows: DataFrame, window: str = "1 day", slide: str | None = None) -> DataFrame:
    """start, j, l, signed_sum, reports for tumbling or sliding windows; batch and stream alike."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    out = rows.groupBy(w.alias("w"), "j", "l").agg(F.sum("sign").cast("bigint").alias("signed_sum"), F.count("*").alias("reports"))
    return out.select(F.col("w.start").alias("start"), "j", "l", "signed_sum", "reports")


def stream_sketch(events: DataFrame, p: Params, window: str = "1 day", slide: str | None = None, lateness: str = "2 days") -> DataFrame:
    """Windowed states of a stream: repeated reports count once, late ones beyond the watermark are dropped."""
    rows = event_reports(events, p).withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["rid"])
    return window_sketch(rows, window, slide)


def session_reports(events: DataFrame, gap: str = "30 minutes", lateness: str = "2 days") -> DataFrame:
    """user_id, start, n, rid: one report for each session of a user: its first event's."""
    rows = events.withWatermark("ts", lateness) if events.isStreaming else events
    grouped = rows.groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return grouped.agg(F.count("*").alias("n"), F.min_by("event_id", "ts").alias("rid")).select("user_id", F.col("w.start").alias("start"), "n", "rid")


def acknowledged(rows: DataFrame, acks: DataFrame, within: str = "1 hour", lateness: str = "2 days") -> DataFrame:
    """Reports that an acknowledgement (rid, ack_ts) followed in time: a join of two streams, both watermarked."""
    a = rows.withWatermark("ts", lateness)
    b = acks.select(F.col("rid").alias("ack_rid"), "ack_ts").withWatermark("ack_ts", lateness)
    on = F.expr(f"rid = ack_rid and ack_ts >= ts and ack_ts <= ts + interval {within}")
    return a.join(b, on).drop("ack_rid")


def scored_stream(events: DataFrame, scores: DataFrame, p: float) -> DataFrame:
    """The event clients of a stream with g (0 where no score is listed) and heavy, by a join with a static score table."""
    listed = scores.select("item", F.col("g").cast("double").alias("g"))
    joined = event_clients(events).join(F.broadcast(listed), "item", "left")
    return joined.withColumn("g", F.coalesce("g", F.lit(0.0))).withColumn("heavy", F.col("g") >= F.lit(p))


def watermark_losses(query) -> int:
    """Rows that the stateful operators of a streaming query have dropped as too late, over the progress that it keeps."""
    return sum(int(op["numRowsDroppedByWatermark"]) for progress in query.recentProgress for op in progress["stateOperators"])


class Budget(StatefulProcessor):
    """How much of the budget a user has spent: reports beyond the limit are withheld."""

    def __init__(self, limit: int):
        self.limit = limit

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.spent = handle.getValueState("spent", "n long")

    def handleInputRows(self, key, rows, timer_values) -> Iterator[pd.DataFrame]:
        spent = self.spent.get()[0] if self.spent.exists() else 0
        for part in rows:
            room = max(0, self.limit - spent)
            sent = part.sort_values("rid").head(room)
            spent += len(sent)
            if len(sent):
                yield sent[["user_id", "rid", "j", "l", "sign"]]
        self.spent.update((spent,))

    def close(self) -> None:
        pass


def limited_reports(rows: DataFrame, limit: int = 1) -> DataFrame:
    """At most `limit` reports of each user over the whole stream."""
    return rows.select("user_id", "rid", "j", "l", "sign").groupBy("user_id").transformWithStateInPandas(
        statefulProcessor=Budget(limit), outputStructType="user_id bigint, rid string, j int, l int, sign int", outputMode="append", timeMode="none"
    )


def save_batches(stream: DataFrame, path: str, checkpoint: str):
    """Writes every micro-batch's state by its number, so that a batch that is run again replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
